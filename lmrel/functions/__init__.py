"""Types, constraints, decoding, prompts, skills and measures."""
