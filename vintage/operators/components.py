"""Distributed connected components by alternating star contraction."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..sources.tables import stored

#: Edges that one task may hold when it contracts them.
TASK_EDGES = 1_000_000


def connected_components(edges: DataFrame, a: str, b: str, max_rounds: int = 60, contract: bool = False) -> DataFrame:
    """(node, component): component is the least node reachable over ``edges``.

    Only nodes of edges between two different, non-null ends appear; the caller
    treats the rest as their own component. Each round points every larger
    neighbour of a node at the least of its neighbourhood, then every smaller
    neighbour likewise; a forest of stars is the fixed point and is reached in
    a logarithmic number of rounds on the graphs met here. Edges live in the
    shared folder between rounds; the driver sees two numbers a round. Minima
    are pre-aggregated before their shuffle, and a node with very many
    neighbours only skews a join, which adaptive execution splits.

    ``contract`` first joins what it can inside tasks of at most TASK_EDGES edges
    each (union-find, in Python): a task returns a forest of its own edges. If
    all edges fit one task, that forest is the answer.
    """
    u, v = F.col("u"), F.col("v")
    now = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where(F.col(a).isNotNull() & F.col(b).isNotNull() & (u != v)).distinct()
    if contract:
        now = stored(now)
        tasks = -(-now.count() // TASK_EDGES)
        now = now.repartition(max(1, tasks)).mapInArrow(_forest, now.schema)
        if tasks <= 1:
            return _labels(stored(now))
        now = now.distinct()
    now, seen = _measured(now)
    for _ in range(max_rounds):
        if not seen[0]:
            break
        both = now.union(now.select(v, u))
        least = both.groupBy(u).agg(F.min(v).alias("m")).select(u, F.least("u", "m").alias("m"))
        large = both.where(v > u).join(least, "u").select(v.alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy(u).agg(F.min(v).alias("m"))
        small = large.join(low, "u").where(v != F.col("m")).select(v.alias("u"), F.col("m").alias("v"))
        now, after = _measured(small.union(low.select(u, F.col("m").alias("v"))).distinct())
        if after == seen:
            break
        seen = after
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return _labels(now)


def _labels(stars: DataFrame) -> DataFrame:
    return stars.select(F.col("u").alias("node"), F.col("v").alias("component")).union(stars.select("v", "v").distinct())


def _forest(batches):
    """Each node of a task's edges with the least node of its tree, roots left out."""
    parent: dict = {}
    schema = None
    for b in batches:
        schema = b.schema
        for x, y in zip(b.column("u").to_pylist(), b.column("v").to_pylist(), strict=True):
            x, y = _root(parent, x), _root(parent, y)
            if x != y:
                parent[max(x, y)] = min(x, y)
    if parent:
        nodes = list(parent)
        yield pa.RecordBatch.from_arrays([pa.array(nodes, schema.field("u").type), pa.array([_root(parent, x) for x in nodes], schema.field("v").type)], ["u", "v"])


def _root(parent: dict, x):
    top = x
    while (up := parent.get(top, top)) != top:
        top = up
    while x != top:
        parent[x], x = top, parent[x]
    return top


def _measured(df: DataFrame) -> tuple[DataFrame, tuple[int, int]]:
    """The stored table with its row count and an order-free digest of its rows."""
    got = Observation()
    out = stored(df.observe(got, F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")))
    return out, (got.get["n"], got.get["x"] or 0)
