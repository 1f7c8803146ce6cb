"""Deletion requests as streams."""
