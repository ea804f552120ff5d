"""Sources that Spark does not have."""
