"""bucketnet plans."""
