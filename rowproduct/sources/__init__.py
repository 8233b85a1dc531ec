"""Matrices from tables, files and generators."""
