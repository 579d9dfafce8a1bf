"""Training-data operators: dedup, tokenising, classification, search, mixing, formatting.

Nothing else in the library imports this subpackage.
"""
