"""Readers and writers of tables and sketches."""
