"""Graph programs over very many overlapping subgraphs, planned and run on Spark DataFrames."""
