"""Training-data operators: scoring, dedup, language, quality, secrets, mixing and tokenizing.

Nothing else in the library imports this subpackage, so it can be removed as a whole.
"""
