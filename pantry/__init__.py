"""Recipe-text normalization, food linking and quantity-weighted embeddings on Spark."""
