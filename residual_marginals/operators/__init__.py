"""Relational and array operators on marginals and residuals."""
