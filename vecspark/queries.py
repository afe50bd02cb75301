"""Every query of the library proper, by name, and its SQL twin."""

from vecspark.plans import relational, vector_queries
from vecspark.streaming import live

QUERIES: dict = {**vector_queries.QUERIES, **relational.QUERIES, **live.QUERIES}
ORACLES: dict = {**vector_queries.ORACLES, **relational.ORACLES, **live.ORACLES}
