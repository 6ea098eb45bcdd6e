"""Splits, negative samples and end-to-end prediction tasks."""
