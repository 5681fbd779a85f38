"""Top-K multi-hop reasoning over knowledge graphs, as Spark DataFrame plans."""
