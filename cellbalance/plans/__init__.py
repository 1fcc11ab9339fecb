"""plans of the rebalancing engine."""
