"""Training-data operators (mixing, near-duplicates, tokenising, scoring, search).

Nothing else in the library imports this subpackage.
"""
