"""Whole partitioning runs, baselines, evaluation and the query catalogue."""
