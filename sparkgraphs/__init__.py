"""Graph analytics on Spark DataFrames: frontier rounds, buckets, histograms, contraction."""
