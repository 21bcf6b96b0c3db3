"""Box queries over many dimensions on Spark: scans, trees, approximation cells, clustered layouts and what picks between them."""
