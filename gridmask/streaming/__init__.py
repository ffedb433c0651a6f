"""Append and windows over streams."""
