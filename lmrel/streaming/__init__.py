"""Language-model answers over streams."""
