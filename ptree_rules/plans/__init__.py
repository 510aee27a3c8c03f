"""Mining plans: the tree miner, its baselines, and the grid of both."""
