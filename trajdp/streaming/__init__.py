"""Histograms of live feeds."""
