"""Measures of accuracy and cost."""
