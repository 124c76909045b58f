"""Standing queries over a change feed."""
