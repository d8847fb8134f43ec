"""Fitting of codebooks, table quantizers and rotations."""
