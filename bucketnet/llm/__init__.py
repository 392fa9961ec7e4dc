"""Operators for preparing language-model training data. Nothing else in bucketnet imports this."""
