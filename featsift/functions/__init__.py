"""Encoders, information measures, criteria and SQL-callable functions."""
