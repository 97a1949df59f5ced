"""Summaries built while segments arrive."""
