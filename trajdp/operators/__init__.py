"""Operators on trajectories, histograms, queries and regions."""
