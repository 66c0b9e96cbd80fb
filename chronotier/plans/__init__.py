"""Checks on logical and physical plans."""
