"""Choosing among models and structures."""
