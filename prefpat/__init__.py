"""Interactive pattern discovery on Spark: mine, sample, ask, learn, repeat."""
