"""Corpus operators for training data: one module for each, registered in queries.py."""
