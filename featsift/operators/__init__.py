"""Counting, relevance, redundancy, greedy selection, baselines, models and measures."""
