"""Training-data operators (text cleaning, near-duplicates, tokens, fixity).

Self-contained: nothing outside this subpackage imports it.
"""
