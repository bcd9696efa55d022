"""Sketch builders, probes, the packed form, baselines and relational operators."""
