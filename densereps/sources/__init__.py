"""Scans, point-set recipes, model and table sinks."""
