"""Model providers, tables and the answer cache."""
