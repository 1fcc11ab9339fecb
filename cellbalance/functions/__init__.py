"""functions of the rebalancing engine."""
