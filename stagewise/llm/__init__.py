"""Training-data operators: extraction, filters, deduplication, mixing and packing.

Nothing outside this package imports it.  Every operator takes and returns
DataFrames; the thin ``opN_*`` queries are in :mod:`stagewise.llm.queries`.
"""
