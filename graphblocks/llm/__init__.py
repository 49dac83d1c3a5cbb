"""Training-data operators: tokenising, duplicate removal, filters, packing.

Nothing outside this subpackage imports it.
"""
