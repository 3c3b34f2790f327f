"""Continuous subgraph matching on Spark: matches that appear or vanish as a labelled graph changes."""
