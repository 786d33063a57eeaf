"""Mechanisms and experiments built from the operators."""
