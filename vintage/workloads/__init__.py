"""Queries on the given tables, and their SQL counterparts."""

from . import pipelines, probing, relational, retrieval

QUERIES = {**probing.QUERIES, **retrieval.QUERIES, **pipelines.QUERIES, **relational.QUERIES}
ORACLE_SQL = {**probing.ORACLE_SQL, **retrieval.ORACLE_SQL, **pipelines.ORACLE_SQL, **relational.ORACLE_SQL}
