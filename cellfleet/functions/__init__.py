"""functions of the spatial engine."""
