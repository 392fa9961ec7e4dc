"""bucketnet functions."""
