"""Relational queries over Spark tables in which some expressions are answered by a language model."""
