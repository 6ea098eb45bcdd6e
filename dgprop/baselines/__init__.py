"""Compact forms of the methods that results are compared with."""
