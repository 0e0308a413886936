"""sift: extensible object-level data skipping on Spark."""
