"""Stages of counting, baselines, indexes and measures."""
