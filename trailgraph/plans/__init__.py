"""Whole-engine plans: configuration, pipeline, measures and the SQL surface."""
