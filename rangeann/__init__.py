"""Vector search under interval predicates on Spark: exact plans, versioned segment-tree graphs, baselines."""
