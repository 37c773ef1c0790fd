"""Training-data operators: mixing, line dedup, media, sharding, extraction, language, quality, toxicity, near-dedup, packing.

Nothing outside this package imports it. Shared rules: ``documents``-like inputs are read by
column name (other columns are ignored or passed through untouched), null texts count as
empty, and intermediate tables go to the folder named in ``spark.checkpoint.dir``.
"""
