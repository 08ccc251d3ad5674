"""levelmine: graph mining by levels of embeddings on Spark DataFrames."""
