"""Training-data operators: near duplicates, line and passage dedup, filters, scoring, tokens, packing.

Nothing outside this subpackage imports it.  Every operator takes and returns
DataFrames; ``queries.py`` registers the thin ``opN_<name>`` queries.
"""
