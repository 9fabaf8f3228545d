"""hopline: shortcut edges and few-hop approximate distances on Spark DataFrames."""
