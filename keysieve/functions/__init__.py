"""Column expressions: hashes, attribute prints and binning."""
