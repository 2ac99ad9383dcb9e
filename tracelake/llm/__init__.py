"""Training-data operators: dedup, licences, language, archives, mixing, packing.

Nothing else in the library imports this subpackage.
"""
