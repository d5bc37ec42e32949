"""Connected components of a graph of links: the library's own."""

from geocentra.graph.components import connected as connected_components

__all__ = ["connected_components"]
