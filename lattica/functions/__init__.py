"""Part of the graph-rule engine."""
