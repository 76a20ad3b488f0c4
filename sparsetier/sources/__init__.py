"""Matrices from tables and generators."""
