"""Whole methods and experiments put together from operators."""
