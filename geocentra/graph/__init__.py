"""Graphs as two relations: vertices and arcs."""
