"""Readers of artifacts."""
