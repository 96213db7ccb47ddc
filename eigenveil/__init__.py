"""Private recognition over image-like vectors, built on Spark."""
