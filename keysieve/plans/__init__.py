"""Star queries, sizing, bounds and measures."""
