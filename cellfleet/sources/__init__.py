"""sources of the spatial engine."""
