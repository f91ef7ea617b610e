"""Topic trees from word co-occurrence moments, on Spark."""
