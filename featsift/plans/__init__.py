"""Datasets, layouts and the choice of a physical strategy."""
