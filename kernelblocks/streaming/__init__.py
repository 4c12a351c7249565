"""Scoring, windows and refresh over streams."""
