"""Training-data operators: quality, duplicates, mixing, encoding, search, filters and personal data.

Nothing else in the library imports this subpackage.
"""
