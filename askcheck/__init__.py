"""Spark-native engine for building and scoring benchmarks of ambiguous and
unanswerable questions over relational databases."""
