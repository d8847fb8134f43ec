"""Restricting a scan to a part of the codes."""
