"""Nearest neighbours: exact blocks, forest of hyperplane trees, sign hashing."""
