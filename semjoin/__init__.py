"""Semantic joins on Spark: language-model joins planned by token cost."""
