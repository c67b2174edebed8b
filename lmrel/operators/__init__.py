"""Row-wise and set functions, cascades, early exit, joins and approximate answers."""
