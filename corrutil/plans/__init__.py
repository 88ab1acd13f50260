"""Mining plans: the correlated miner by levels and by prefixes, and the baselines."""
