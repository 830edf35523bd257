"""Private margin-classifier analytics on Spark."""
