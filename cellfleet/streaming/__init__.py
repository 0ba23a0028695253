"""streaming of the spatial engine."""
