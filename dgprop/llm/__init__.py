"""Training-data operators: similarity joins, mixing, scoring, packing, filters.

Nothing outside this subpackage imports it.
"""
