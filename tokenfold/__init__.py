"""Training-free prompt compression on Spark: chunking, spectral hashing and routing of tokens."""
