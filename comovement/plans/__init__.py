"""Partitioning in time and space, and the choice of a method."""
