"""Training-data operators: near and exact duplicates, personal data, repeated passages, encoding, mixing, quality, pages, toxicity.

Nothing outside this folder imports it.  ``queries.py`` holds the registered queries.
"""
