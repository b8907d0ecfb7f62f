"""Graphs read from tables, files and streams."""
