"""Nearest neighbours: exact, cells, hyperplanes, layered graphs."""
