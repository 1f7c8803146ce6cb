"""Deletion propagation: regression models kept up to date as views over their training rows."""
