"""Schema discovery and value profiling of JSON collections on Spark."""
