"""Encoding, updates, answers and features over streams."""
