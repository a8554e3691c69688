"""Monoids, aggregates built on them, and user functions."""
