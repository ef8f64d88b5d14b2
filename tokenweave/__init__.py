"""Free-text record linkage on Spark: bags of tokens, pruned inverted indexes, two-round scoring."""
