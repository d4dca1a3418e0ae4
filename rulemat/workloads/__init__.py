"""Rule sets, data sets and experiments on the given tables."""
