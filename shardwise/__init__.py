"""shardwise: balanced hypergraph partitioning and data-preparation operators on PySpark DataFrames."""
