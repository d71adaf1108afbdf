"""seedcluster: local motif clustering on Spark DataFrames."""
