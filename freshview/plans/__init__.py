"""Node trees of views, their keys, and the push-down of the key-hash filter."""
