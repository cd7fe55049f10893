"""Training-data operators: search, token output, fixity, dedup, packing, privacy, language.

Nothing else in the library imports this subpackage.
"""
