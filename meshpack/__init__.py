"""Compact adaptive-mesh trees on Spark: layout, pruning and tree-aware compression."""
