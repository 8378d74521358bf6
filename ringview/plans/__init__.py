"""Plan objects on the driver: queries, hypergraphs, variable orders, view trees, delta trees.  They hold no data."""
