"""Block building, intersection rounds, baselines, measures and the relational operators around them."""
