"""Fitted models as arrays and as tables."""
