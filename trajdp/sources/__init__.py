"""Trajectory sources and files."""
