"""Expression trees, the rule-based planner, strategies and the SQL surface."""
