"""All queries of the engine and their SQL."""

from .plans import experiments, relational, vectors, workloads
from .streaming import streams

QUERIES: dict = {**workloads.QUERIES, **relational.QUERIES, **vectors.QUERIES, **streams.QUERIES, **experiments.QUERIES}
ORACLE_SQL: dict = {**workloads.ORACLE_SQL, **relational.ORACLE_SQL, **vectors.ORACLE_SQL, **streams.ORACLE_SQL}
