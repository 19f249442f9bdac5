"""Join strategies, baselines and relational operators."""
