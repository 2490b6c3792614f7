"""Approximate, up-to-date answers on stale materialised views, native to Spark."""
