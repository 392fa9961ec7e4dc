"""bucketnet streaming."""
