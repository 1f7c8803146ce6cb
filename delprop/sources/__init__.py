"""Readers, sinks and features."""
