"""Query-agnostic track extraction and track analytics on Spark."""
