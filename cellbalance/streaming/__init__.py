"""streaming of the rebalancing engine."""
