"""Marginals over streams."""
