"""Propagation on graphs that change, as DataFrame plans."""
