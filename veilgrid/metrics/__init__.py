"""Distances between histograms."""
