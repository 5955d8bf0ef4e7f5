"""Evidence-graph retrieval on Spark: index, subgraph search, fusion, baselines and measures."""
