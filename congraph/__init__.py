"""Join-based pattern matching over congruence graphs, on Spark."""
