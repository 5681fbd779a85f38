"""Where graphs and vectors come from, and where answers go."""
