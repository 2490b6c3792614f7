"""Streaming and mini-batch loops."""
