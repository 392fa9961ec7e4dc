"""All queries of the library and their SQL counterparts."""

from bucketnet.queries import relational, retrieval, training

QUERIES = retrieval.QUERIES | training.QUERIES | relational.QUERIES
ORACLES = retrieval.ORACLES | training.ORACLES | relational.ORACLES
