"""Distinct counts, dependencies and the operators around them."""
