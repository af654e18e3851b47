"""Operators on DataFrames: mechanisms, histograms, proposals, splits, leaves, sampling."""
