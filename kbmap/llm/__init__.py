"""Training-data operators: filters, near-duplicate search, mixing, encoding and archive formats.

Nothing else in the library imports this subpackage; it may be removed whole.
"""
