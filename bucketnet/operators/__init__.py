"""bucketnet operators."""
