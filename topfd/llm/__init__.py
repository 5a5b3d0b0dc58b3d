"""Training-data operators: search, language ID, dedup, mixing, filtering, counting, packing, extraction.

Nothing outside this subpackage imports it; ``registry`` holds the queries that ``__spark_entry__`` adds.
"""
