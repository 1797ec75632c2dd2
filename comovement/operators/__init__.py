"""Joins, classification, refinement, baselines and the surrounding operators."""
