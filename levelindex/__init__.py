"""Leveled vector index on Spark: recursive partitioning, batch search, baselines, measures and updates."""
