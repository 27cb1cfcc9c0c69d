"""Novelty detection over text streams with Spark."""
