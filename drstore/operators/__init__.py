"""Methods of the store: collections, dictionaries, suffixes, factors, codecs, baselines, retrieval and measures."""
