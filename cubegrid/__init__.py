"""cubegrid: multi-dimensional cube indexes and their baselines for range queries on Spark."""
