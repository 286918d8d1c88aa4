"""Releasing records as they arrive."""
