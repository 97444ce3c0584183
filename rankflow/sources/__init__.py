"""Readers of edge lists, Matrix Market files, and synthetic graphs."""
