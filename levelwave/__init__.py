"""levelwave: level-synchronous traversal of very large graphs on Spark DataFrames."""
