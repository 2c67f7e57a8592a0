"""Maintenance of cell maps and windowed counts over streams."""
