"""operators of the rebalancing engine."""
