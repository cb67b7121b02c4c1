"""Training-data operators: deduplication, packing, scoring, labelling and search.

Nothing outside this subpackage imports it.  Every operator is a function from
DataFrames to a DataFrame; the thin contract queries live in ``queries.py``.
"""
