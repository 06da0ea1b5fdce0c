"""Counting mechanisms, exact counts, baselines, costs and bounds."""
