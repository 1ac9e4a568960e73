"""Training-data operators: sharding, licence scans, deduplication, quality,
language, packing, URL filters and tokenisation.

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its
queries only when it is present.
"""
