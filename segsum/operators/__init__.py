"""Segmentation, summaries, cube planning, estimates, baselines and measures."""
