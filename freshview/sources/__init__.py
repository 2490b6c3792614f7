"""Readers, change sets and versioned sinks."""
