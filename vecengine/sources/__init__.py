"""Readers, derived vector views, synthetic data."""
