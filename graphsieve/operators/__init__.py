"""Operators of the reduction pipeline and the relational operators around it."""
