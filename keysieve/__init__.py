"""Predicate-aware membership sketches for Spark, and the operators around them."""
