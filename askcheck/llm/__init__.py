"""Training-data operators: tokenisation, packing, quality, dedup, PII, search.

Nothing outside this folder imports it; ``__spark_entry__`` adds its queries
only if it can be imported.
"""
