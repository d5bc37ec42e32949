"""Approximate sets: registers, bit patterns, and their sizes."""
