"""Operations of a training-data pipeline: mixing, quality rules, extraction, tokens, deduplication, search.

Nothing outside this package imports it.  Arrow-batched NumPy code runs where a byte-level
method has no DataFrame form; joins, groupings and sorts are Spark's.
"""
