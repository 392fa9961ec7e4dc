"""bucketnet: hash-sampled training and retrieval of very wide sparse models on Spark."""
