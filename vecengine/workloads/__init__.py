"""Experiments."""
