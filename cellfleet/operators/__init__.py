"""operators of the spatial engine."""
