"""Structured Streaming operators and sketch upkeep."""
