"""Training-data operators: deduplication, filters, classifiers, packing.

Nothing outside this subpackage imports it.
"""
