"""Array kernels: one string at a time, numpy and plain Python, no Spark."""
