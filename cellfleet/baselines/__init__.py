"""baselines of the spatial engine."""
