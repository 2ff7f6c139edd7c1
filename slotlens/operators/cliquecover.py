"""Groups of mutually similar vectors: greedy, exact, and parallel rounds for one large graph."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slotlens.functions import covers
from slotlens.storage import written

EXACT_ITEMS = 40

def greedy(vectors: DataFrame, s0: float, item: str = "slot", group: str = "vp_id", keys: list[str] | None = None, kind: str = "int", **how) -> DataFrame:
    """(keys, item, group): the greedy cover of each series' threshold graph, ties by least item."""
    return _per_series(vectors, lambda v: covers.greedy(covers.threshold_graph(covers.distances(v), s0), d=covers.distances(v), **how), item, group, keys, kind)


def exact(vectors: DataFrame, s0: float, item: str = "slot", group: str = "vp_id", keys: list[str] | None = None, kind: str = "int") -> DataFrame:
    """As ``greedy`` with the least number of groups; at most ``EXACT_ITEMS`` items a series."""

    def run(v: np.ndarray) -> np.ndarray:
        if len(v) > EXACT_ITEMS:
            raise ValueError(f"the exact cover takes at most {EXACT_ITEMS} items")
        return covers.exact(covers.threshold_graph(covers.distances(v), s0))

    return _per_series(vectors, run, item, group, keys, kind)


def _per_series(vectors: DataFrame, label, item: str, group: str, keys: list[str] | None, kind: str) -> DataFrame:
    keys = keys or ["series_id"]
    types = dict(vectors.dtypes)
    schema = ", ".join(f"{k} {types[k]}" for k in keys) + f", {item} {kind}, {group} int"

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(item)
        out = pdf[[*keys, item]].copy()
        out[group] = label(pdf[["theta", "mad"]].to_numpy(float)).astype(np.int32)
        return out

    return vectors.select(*keys, F.col(item).cast(kind).alias(item), "theta", "mad").groupBy(*keys).applyInPandas(run, schema)


def greedy_rounds(vertices: DataFrame, edges: DataFrame, ties: str = "hash", most_rounds: int = 1000) -> DataFrame:
    """(v, seed): the greedy cover (residual degree, neighbours in order of ids) of one graph, many seeds a round.

    Every uncovered vertex that ranks first (degree, then tie) within two steps of the uncovered graph grows its
    clique at once; two such vertices share no neighbour, so the outcome is that of one after the other. ties: ``id``
    is the sequential cover itself, whose rounds may grow with the length of a path; ``hash`` breaks ties by a hash
    of the round, so that rounds grow with the logarithm. Rounds that run out raise: a cover is whole or not returned.
    ``edges`` holds (a, b) with a < b. Each round is written to the shared folder, which cuts lineage.
    """
    free = written(vertices.select(F.col("v").cast("bigint").alias("v")).distinct())
    both = edges.select(F.col("a").cast("bigint").alias("a"), F.col("b").cast("bigint").alias("b")).where("a != b")
    both = written(both.unionAll(both.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    done = None
    for turn in range(most_rounds):
        tie = F.xxhash64("v", F.lit(turn)) if ties == "hash" else F.lit(0)
        rank = free.join(both.groupBy("a").count(), F.col("v") == F.col("a"), "left").select(
            "v", F.struct(F.coalesce("count", F.lit(0)).alias("deg"), tie.alias("tie"), (-F.col("v")).alias("id")).alias("p")
        )

        def spread(df, name):
            seen = both.join(df, F.col("b") == F.col("v")).groupBy("a").agg(F.max("p").alias("q"))
            joined = df.join(seen, F.col("v") == F.col("a"), "left")
            return joined.select("v", F.greatest("p", F.coalesce("q", "p")).alias("p"))

        first = spread(spread(rank, "one"), "two").withColumnRenamed("p", "most").withColumnRenamed("v", "w")
        seeds = written(rank.join(first, F.col("v") == F.col("w")).where("p = most").select(F.col("v").alias("seed")))
        around = both.join(seeds, F.col("a") == F.col("seed")).select("seed", F.col("b").alias("w"))
        inner = both.join(around.select("seed", F.col("w").alias("x")), F.col("a") == F.col("x")).join(
            around.select(F.col("seed").alias("s2"), F.col("w").alias("y")), (F.col("seed") == F.col("s2")) & (F.col("b") == F.col("y"))
        )
        near = around.join(inner.select("seed", F.col("x").alias("w"), "y"), ["seed", "w"], "left").groupBy("seed", "w").agg(F.collect_list("y").alias("ys"))

        def grow(pdf: pd.DataFrame) -> pd.DataFrame:
            pdf = pdf.sort_values("w")
            allowed, taken = None, []
            for w, ys in zip(pdf["w"], pdf["ys"], strict=True):
                if allowed is None or w in allowed:
                    taken.append(w)
                    allowed = set(ys) if allowed is None else allowed & set(ys)
            return pd.DataFrame({"v": taken, "seed": int(pdf["seed"].iloc[0])})

        joined = near.groupBy("seed").applyInPandas(grow, "v long, seed long")
        taken = written(joined.unionByName(seeds.select(F.col("seed").alias("v"), "seed")))
        done = taken if done is None else done.unionAll(taken)
        free = written(free.join(taken, "v", "left_anti"))
        if not free.take(1):
            return done
        gone = taken.select("v")
        both = written(both.join(gone, F.col("a") == F.col("v"), "left_anti").join(gone, F.col("b") == F.col("v"), "left_anti"))
    raise RuntimeError(f"cover not whole after {most_rounds} rounds")


def violations(groups: DataFrame, vectors: DataFrame, s0: float, item: str = "slot", group: str = "vp_id") -> DataFrame:
    """One row of counts that a valid cover makes zero: pairs below s0 inside a group, items not covered exactly once."""
    from slotlens.operators.similarity import pairs

    g = groups.select("series_id", F.col(item).alias("i"), F.col(group).alias("g"))
    p = pairs(vectors, item)
    a, b = g.alias("ga"), g.alias("gb")
    inside = p.join(a, (p["series_id"] == F.col("ga.series_id")) & (p["a"] == F.col("ga.i"))).join(
        b, (p["series_id"] == F.col("gb.series_id")) & (p["b"] == F.col("gb.i"))
    )
    bad = inside.where((F.col("ga.g") == F.col("gb.g")) & (F.col("dist") * s0 > 1 + 1e-9)).agg(F.count("*").alias("pairs_below"))
    times = vectors.join(g.groupBy("series_id", "i").count(), (vectors["series_id"] == g["series_id"]) & (vectors[item] == g["i"]), "left")
    lost = times.agg(F.count_if(F.coalesce("count", F.lit(0)) != 1).alias("not_once"))
    return bad.crossJoin(lost)
