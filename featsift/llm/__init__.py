"""Operators over a text corpus for training data.  Nothing else in the package imports this subpackage."""
