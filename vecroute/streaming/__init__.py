"""Queries and their partial answers as streams."""
