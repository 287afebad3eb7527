"""Single-node PageRank on undirected graphs, written as Spark DataFrame plans."""
