"""Readers, the experiment datasets, and the summary store."""
