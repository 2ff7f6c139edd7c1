"""Connected components by alternating star contraction, as plain joins and aggregates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slotlens.llm.common import BROADCAST_ROWS, forget, materialise

#: Parts into which the edges of one vertex are dealt where its least neighbour cannot be broadcast.
SALTS = 64


def _with_least(edges: DataFrame, rows: int) -> DataFrame:
    """Edges (u, v) with m, the least neighbour of u.

    A hot u has one row a salt in all but the first exchange, and its edges meet m dealt over the salts.
    """
    if rows <= BROADCAST_ROWS:
        return edges.join(F.broadcast(edges.groupBy("u").agg(F.min("v").alias("m"))), "u")
    salted = edges.withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(SALTS)))
    parts = salted.groupBy("u", "salt").agg(F.min("v").alias("m"))
    least = parts.groupBy("u").agg(F.min("m").alias("m"))
    return salted.join(parts.select("u", "salt").join(least, "u"), ["u", "salt"]).drop("salt")


def _large_star(edges: DataFrame, rows: int) -> DataFrame:
    both = edges.select("u", "v").unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    moved = _with_least(both, 2 * rows).where(F.col("v") > F.col("u"))
    return moved.select(F.col("v").alias("u"), F.least("u", "m").alias("v")).where(F.col("u") != F.col("v")).distinct()


def _small_star(edges: DataFrame, rows: int) -> DataFrame:
    # Every edge points from the larger end u to the smaller end v.
    moved = _with_least(edges, rows)
    out = moved.select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(moved.select("u", F.col("m").alias("v")))
    return out.where(F.col("u") != F.col("v")).distinct()


def components(edges: DataFrame, most_rounds: int = 200) -> DataFrame:
    """(node, component) for every node of the undirected edges (u, v); the component is its least node.

    Each round is two star contractions and is written to the shared folder, which cuts lineage; rounds grow
    with the logarithm of the longest path, and an end that is not reached raises. Neighbour lists are never
    collected: a star's centre is met by an aggregate, and by a broadcast or a join dealt over salts. No edges: an
    empty result.
    """
    edges = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where(F.col("u") != F.col("v"))
    edges, last = materialise(edges.distinct()), None
    rows = edges.count()
    for _ in range(most_rounds):
        new = materialise(_small_star(_large_star(edges, rows), rows))
        forget(edges)
        edges = new
        # At the fixed point every edge ends in a root, so that no u is also a v, and the sum stays.
        mark = edges.select(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == last:
            break
        last, rows = mark, mark[0]
    else:
        raise RuntimeError(f"components not settled after {most_rounds} rounds")
    roots = edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionAll(roots)
