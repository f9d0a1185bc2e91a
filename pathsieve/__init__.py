"""Label-pattern reachability on very large edge-labelled digraphs, built on Spark DataFrames."""
