"""Selection of small pattern sets from large pools with mergeable bottom-k sketches, on Spark DataFrames."""
