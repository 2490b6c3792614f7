"""Column functions: key hashes, bands, and their SQL forms."""
