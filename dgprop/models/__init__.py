"""Predictors without graph operations: dense, recurrent and attention models."""
