"""Context-model analytics on Spark: counting, binning, clustering and adaptive modelling of symbol sequences."""
