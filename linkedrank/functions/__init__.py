"""Column functions: tokens, statistics, scores and ceilings."""
