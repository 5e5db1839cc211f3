"""Graph algorithms, vector operations, baselines and relational operators."""
