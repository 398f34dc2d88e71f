"""Connected components of an edge list by alternating star contraction.

Each round points every node's larger neighbours at the smallest node it sees, then every node's
smaller neighbours at the smallest of those. Labels only fall, a round moves a bounded number of rows
per edge, and the edge list is written to the shared folder after each round, so lost executors cost
one round. A hub is never collected: minima are aggregated before the shuffle, and its neighbours are
joined to its minimum.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..runtime import discard, materialise


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One contraction of undirected ``edges`` (a > b)."""
    if large:
        sides = edges.select("a", "b").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    else:
        sides = edges
    least = sides.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    joined = sides.join(least, "a")
    kept = joined.where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b")) if large else (
        joined.where(F.col("b") != F.col("m")).select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(least.select("a", F.col("m").alias("b")))
    )
    return kept.where("a > b").distinct()


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, root): the smallest node of its component, for each node that has an edge to another.

    ``edges`` has columns a and b of one orderable type; loops, nulls and repeated rows change nothing.
    """
    edges = edges.where("a is not null and b is not null and a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    edges = materialise(edges, "edges")
    total = F.struct(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h"))
    state = edges.agg(total.alias("t")).first()["t"]
    for _ in range(most_rounds):
        if not state["n"]:
            break
        after = materialise(_star(_star(edges, True), False), "edges")
        now = after.agg(total.alias("t")).first()["t"]
        discard(edges)
        edges = after
        if now == state:
            break
        state = now
    else:
        raise RuntimeError("the components did not settle")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
