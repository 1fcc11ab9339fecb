"""sources of the rebalancing engine."""
