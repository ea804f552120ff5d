"""From a parsed query to the cheapest plan of kernels."""
