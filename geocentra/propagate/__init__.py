"""Growing balls round by round along the arcs."""
