"""twinfold: duplicate detection and preservative deduplication on Spark DataFrames."""
