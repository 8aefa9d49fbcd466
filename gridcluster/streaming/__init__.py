"""Scoring and counting of streams with a fitted model."""
