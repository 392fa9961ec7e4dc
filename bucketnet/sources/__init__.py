"""bucketnet sources."""
