"""Piecewise-linear segmentation of time-ordered signals on Spark."""
