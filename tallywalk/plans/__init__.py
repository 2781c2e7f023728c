"""Scores, experiments, and the queries with their SQL twins."""
