"""Private supervised embeddings and retrieval on Spark."""
