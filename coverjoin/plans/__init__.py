"""Planning on query-sized data, in the driver: hypergraphs, covers, bounds, trees, rules."""
