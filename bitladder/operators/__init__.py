"""Encoders, matching, selection, baselines and measures."""
