"""Refresh, cleaning, estimation, intervals, outlier sets and measures."""
