"""Operators of the reuse analysis."""
