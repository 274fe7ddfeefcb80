"""A Spark-native compressed document store with random access, its baselines and its measures."""
