"""plans of the spatial engine."""
