"""Top-K lists, hops, paths, lookups and the baselines they are compared with."""
