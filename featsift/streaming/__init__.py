"""Counts that follow a stream of events: windows, running rankings, drift."""
