"""Choices made before a DataFrame plan exists, and the SQL surface."""
