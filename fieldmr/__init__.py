"""Multi-resolution, error-bounded storage of numeric fields as Spark DataFrame plans."""
