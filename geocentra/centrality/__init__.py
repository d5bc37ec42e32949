"""Measures from the number of nodes at each distance."""
