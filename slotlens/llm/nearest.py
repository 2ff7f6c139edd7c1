"""Nearest neighbours by learned partitions of a neighbour graph (op 9)."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slotlens.llm.common import materialise

#: The index is fitted on at most so many distinct vectors, those of least hash; every vector is indexed.
FIT_ROWS = 12_000
#: Neighbours per vector in the graph, rounds of balanced refinement, epochs and width of the router.
GRAPH, ROUNDS, EPOCHS, HIDDEN = 10, 12, 30, 96
#: Vectors of one partition held by one task; larger partitions are dealt into blocks by hash.
BLOCK = 20_000


@dataclass(frozen=True)
class Router:
    """One hidden layer from a unit vector to log-probabilities of the partitions."""

    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: np.ndarray

    def shares(self, x: np.ndarray) -> np.ndarray:
        z = np.maximum(x @ self.w1 + self.b1, 0) @ self.w2 + self.b2
        z = np.exp(z - z.max(axis=1, keepdims=True, initial=-np.inf))
        return z / z.sum(axis=1, keepdims=True)


@dataclass(frozen=True)
class Index:
    """Where vectors are kept and where queries look: a router each, and the probability mass that a query probes.

    Vectors go by direction and length, as long ones are near to more queries; queries by direction alone.
    """

    keep: Router
    look: Router
    longest: float
    mass: float

    def home(self, x: np.ndarray) -> np.ndarray:
        return self.keep.shares(levelled(x, self.longest)).argmax(axis=1).astype(np.int32)

    def probes(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Partitions from likely to unlikely, and how many of them lie within the mass."""
        p = self.look.shares(unit(x))
        order = np.argsort(-p, axis=1, kind="stable")
        return order.astype(np.int32), (mass_before(p, order) <= self.mass).sum(axis=1).astype(np.int32)


def mass_before(p: np.ndarray, order: np.ndarray) -> np.ndarray:
    """Probability of all partitions that a query probes earlier, in its order."""
    ranked = np.take_along_axis(p, order, axis=1)
    return np.cumsum(ranked, axis=1) - ranked


def unit(x: np.ndarray) -> np.ndarray:
    norm = np.linalg.norm(x, axis=1, keepdims=True)
    return x / np.where(norm > 0, norm, 1)


def levelled(x: np.ndarray, longest: float) -> np.ndarray:
    """Unit vectors with one more component that makes up for what each lacks in length."""
    x = x / longest
    return np.hstack([x, np.sqrt(np.maximum(0, 1 - (x * x).sum(axis=1, keepdims=True)))])


def neighbour_graph(x: np.ndarray, k: int) -> np.ndarray:
    """Indices of the k nearest other rows by inner product, by blocks of rows."""
    k = min(k, len(x) - 1)
    out = np.empty((len(x), k), np.int64)
    for at in range(0, len(x), 1024):
        s = x[at : at + 1024] @ x.T
        s[np.arange(len(s)), at + np.arange(len(s))] = -np.inf
        out[at : at + 1024] = np.argpartition(-s, k - 1, axis=1)[:, :k]
    return out


def balanced_partition(x: np.ndarray, graph: np.ndarray, parts: int, rng: np.random.Generator) -> np.ndarray:
    """Labels of equal-size parts that cut few graph edges: a balanced start by centres, then capacity-bound moves
    of each vertex to the part that holds most of its neighbours."""
    n = len(x)
    room = -(-n // parts)
    centres = x[rng.choice(n, parts, replace=False)]
    for _ in range(6):
        nearest = (x @ centres.T).argmax(axis=1)
        sums = np.zeros_like(centres)
        np.add.at(sums, nearest, x)
        filled = np.bincount(nearest, minlength=parts) > 0
        centres[filled] = unit(sums[filled])
    label = _fill(x @ centres.T, room)
    ends = np.concatenate([graph.ravel(), np.repeat(np.arange(n), graph.shape[1])])
    starts = np.concatenate([np.repeat(np.arange(n), graph.shape[1]), graph.ravel()])
    for _ in range(ROUNDS):
        votes = np.zeros((n, parts), np.float32)
        np.add.at(votes, (starts, label[ends]), 1)
        votes += 1e-3 * (x @ centres.T)
        new = _fill(votes, room)
        if (new == label).all():
            break
        label = new
    return label


def _fill(gain: np.ndarray, room: int) -> np.ndarray:
    """Each row to its best part that has room, rows with the most to lose first."""
    n, parts = gain.shape
    two = np.partition(gain, -2, axis=1)[:, -2:] if parts > 1 else np.zeros((n, 2))
    order = np.argsort(-(two[:, 1] - two[:, 0]), kind="stable")
    ranked = np.argsort(-gain, axis=1, kind="stable")
    left, label = np.full(parts, room), np.empty(n, np.int64)
    for i in order:
        for p in ranked[i]:
            if left[p]:
                label[i] = p
                left[p] -= 1
                break
    return label


def train_router(x: np.ndarray, target: np.ndarray, rng: np.random.Generator) -> Router:
    """Adam on the cross entropy with soft targets, a row of weights over the partitions for each vector."""
    (n, d), parts = x.shape, target.shape[1]
    target = target.astype(np.float32)
    target /= target.sum(axis=1, keepdims=True)
    p = [
        (rng.standard_normal((d, HIDDEN)) * (2 / d) ** 0.5).astype(np.float32) * 2,
        np.zeros(HIDDEN, np.float32),
        (rng.standard_normal((HIDDEN, parts)) * (1 / HIDDEN) ** 0.5).astype(np.float32),
        np.zeros(parts, np.float32),
    ]
    m, v, t = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p], 0
    x = x.astype(np.float32)
    for _ in range(EPOCHS):
        for rows in np.array_split(rng.permutation(n), max(1, n // 256)):
            h = np.maximum(x[rows] @ p[0] + p[1], 0)
            z = h @ p[2] + p[3]
            z = np.exp(z - z.max(axis=1, keepdims=True))
            miss = (z / z.sum(axis=1, keepdims=True) - target[rows]) / len(rows)
            back = (miss @ p[2].T) * (h > 0)
            grads = [x[rows].T @ back, back.sum(axis=0), h.T @ miss, miss.sum(axis=0)]
            t += 1
            for i, g in enumerate(grads):
                m[i] = 0.9 * m[i] + 0.1 * g
                v[i] = 0.999 * v[i] + 0.001 * g * g
                p[i] -= 3e-3 * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
    return Router(*p)


def votes(graph: np.ndarray, label: np.ndarray, parts: int) -> np.ndarray:
    """How many of each vector's neighbours lie in each part."""
    out = np.zeros((len(graph), parts))
    np.add.at(out, (np.repeat(np.arange(len(graph)), graph.shape[1]), label[graph].ravel()), 1)
    return out


def fit(vectors: np.ndarray, parts: int, k: int, recall: float, seed: int = 5) -> Index:
    """The routers, and the least probability mass to probe whose measured recall meets the aim.

    Neighbours are those of the largest inner product throughout. A tenth of the vectors (2 000 at most) stays out of
    the training and plays the queries of that measurement, against all fitted vectors; in the whole table
    neighbours are nearer still than in a sample of it.
    """
    rng = np.random.default_rng(seed)
    longest = float(np.linalg.norm(vectors, axis=1).max())
    asked = max(1, min(2000, len(vectors) // 10))
    kept = vectors[asked:]
    level = levelled(kept, longest)
    graph = neighbour_graph(kept, GRAPH)
    label = balanced_partition(level, graph, parts, rng)
    own = votes(graph, label, parts)
    own[np.arange(len(kept)), label] += 1
    keep = train_router(level, own, rng)
    home = keep.shares(levelled(vectors, longest)).argmax(axis=1)
    look = train_router(unit(kept), votes(graph, home[asked:], parts), rng)
    p = look.shares(unit(vectors[:asked]))
    order = np.argsort(-p, axis=1, kind="stable")
    before = np.empty_like(p)
    np.put_along_axis(before, order, mass_before(p, order), axis=1)
    needed = np.sort(np.take_along_axis(before, home[neighbour_graph(vectors, k)[:asked]], axis=1).ravel())
    return Index(keep, look, longest, float(needed[min(len(needed), int(np.ceil(recall * len(needed)))) - 1]))


def usable(rows: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """(vec_id, vector) without rows whose id or vector is null, zero, or holds a null, NaN or infinite component."""
    v = F.col(embedding).cast("array<double>")
    fine = ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    some = F.exists(v, lambda x: x != 0)
    return rows.where(F.col(vec_id).isNotNull() & F.col(embedding).isNotNull() & fine & some).select(
        F.col(vec_id).cast("long").alias("vec_id"), v.alias("vector")
    )


def partitions(n: int, k: int) -> int:
    """One a block of vectors between 16 and 256 (the model stays small); fewer below that, of four lists' worth each."""
    return max(1, min(256, max(n // BLOCK, min(16, n // (4 * k)))))


def search(
    rows: DataFrame,
    query_every: int = 20,
    k: int = 20,
    recall: float = 0.96,
    fit_rows: int = FIT_ROWS,
    vec_id: str = "vec_id",
    embedding: str = "embedding",
) -> DataFrame:
    """query_id, rank, vec_id, score: each query's k nearest other vectors by inner product, best first, ties to smaller id.

    Queries are the rows whose id is divisible by ``query_every``. Null, zero and non-finite vectors and null ids take no
    part; vectors of different lengths have no inner product, so that each length is an index of its own. Equal
    vectors collapse to one, which keeps the k + 1 least of its ids: no later one can enter a list of k, so a hot
    vector loses nothing. Distinct vectors are indexed in the partition that the router gives; a query is scored exactly
    against its likeliest partitions, as many as hold the probability that the fit found to reach ``recall``, block
    by block, and keeps k of each block. A query whose probed partitions hold fewer than k vectors is scored against
    all. An empty table gives an empty result; repeated ids count as candidates each.
    """
    good = materialise(usable(rows, vec_id, embedding).withColumn("key", F.xxhash64("vector")))
    lengths = sorted(r.n for r in good.select(F.size("vector").alias("n")).distinct().collect())
    if not lengths:
        return rows.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    found = [_search(good.where(F.size("vector") == n), n, query_every, k, recall, fit_rows) for n in lengths]
    return reduce(DataFrame.unionByName, found)


def _search(good: DataFrame, length: int, query_every: int, k: int, recall: float, fit_rows: int) -> DataFrame:
    # The least ids of each vector: first inside a salt, then over salts, so that no task sorts a whole hot group.
    salted = Window.partitionBy("key", "vector", F.pmod(F.xxhash64("vec_id"), F.lit(64))).orderBy("vec_id")
    over = Window.partitionBy("key", "vector").orderBy("vec_id")
    few = good.withColumn("r", F.row_number().over(salted)).where(F.col("r") <= k + 1)
    few = few.withColumn("r", F.row_number().over(over)).where(F.col("r") <= k + 1)
    distinct = materialise(few.groupBy("key", "vector").agg(F.sort_array(F.collect_list("vec_id")).alias("ids")))
    n = distinct.count()
    parts = partitions(n, k)
    if parts == 1:  # too few to part: one home for all
        flat = Router(np.zeros((length + 1, 1)), np.zeros(1), np.zeros((1, 1)), np.zeros(1))
        index_ = Index(flat, Router(flat.w1[1:], flat.b1, flat.w2, flat.b2), 1.0, 1.0)
    else:
        sample = distinct.select("key", "vector").orderBy("key", "vector").limit(fit_rows).toArrow()
        index_ = fit(np.array(sample.column("vector").to_pylist(), float), parts, k, recall)
    blocks = max(1, -(-n // (parts * BLOCK)))

    def matrix(batch: pa.RecordBatch) -> np.ndarray:
        return batch.column("vector").flatten().to_numpy(zero_copy_only=False).reshape(len(batch), length)

    def settle(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(index_.home(matrix(batch)))], [*batch.schema.names, "part"])

    def ask(batches):
        for batch in batches:
            best, few = index_.probes(matrix(batch))
            yield pa.RecordBatch.from_arrays(
                [*batch.columns, pa.array(list(best), pa.list_(pa.int32())), pa.array(few)], [*batch.schema.names, "best", "few"]
            )

    block = F.pmod(F.col("key"), F.lit(blocks)).cast("int")
    index = materialise(
        distinct.mapInArrow(settle, "key long, vector array<double>, ids array<long>, part int").select("part", block.alias("block"), "ids", "vector")
    )
    held = {r.part: r["count"] for r in index.groupBy("part").count().collect()}
    asked = good.where(F.pmod("vec_id", F.lit(query_every)) == 0).select("vec_id", "vector").distinct()
    asked = asked.mapInArrow(ask, "vec_id long, vector array<double>, best array<int>, few int")
    sizes = F.array(*(F.lit(held.get(p, 0)) for p in range(parts)))
    chosen = F.slice("best", F.lit(1), F.col("few"))
    enough = F.aggregate(chosen, F.lit(0), lambda a, p: a + F.get(sizes, p)) > k
    asked = asked.select("vec_id", "vector", F.explode(F.when(enough, chosen).otherwise(F.col("best"))).alias("part"))
    asked = asked.select("part", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), "vec_id", "vector")

    def near(queries: pa.Table, known: pa.Table) -> pa.Table:
        empty = pa.table({"query_id": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        if not len(queries) or not len(known):
            return empty
        base = known.column("vector").combine_chunks().flatten().to_numpy().reshape(len(known), -1)
        ids = known.column("ids").to_pylist()
        least = np.array([i[0] for i in ids])
        order = np.argsort(least, kind="stable")
        base, ids = base[order], [ids[i] for i in order]
        q = queries.column("vector").combine_chunks().flatten().to_numpy().reshape(len(queries), -1)
        who = queries.column("vec_id").to_numpy()
        out_q, out_v, out_s = [], [], []
        for at in range(0, len(q), 256):
            s = q[at : at + 256] @ base.T
            take = min(k + 1, s.shape[1])
            # Every vector that ties with the last one taken stays: ties go by id further down.
            limit = np.partition(s, s.shape[1] - take, axis=1)[:, s.shape[1] - take]
            for i, row in enumerate(s):
                hit = np.flatnonzero(row >= limit[i] - 1e-9)
                me = int(who[at + i])
                scores = [(float(np.dot(q[at + i], base[j])), v) for j in hit for v in ids[j] if v != me]
                scores.sort(key=lambda x: (-x[0], x[1]))
                for s1, v in scores[:k]:
                    out_q.append(me)
                    out_v.append(v)
                    out_s.append(s1)
        return pa.table({"query_id": pa.array(out_q, pa.int64()), "vec_id": pa.array(out_v, pa.int64()), "score": pa.array(out_s, pa.float64())})

    found = (
        asked.groupBy("part", "block")
        .cogroup(index.groupBy("part", "block"))
        .applyInArrow(near, "query_id long, vec_id long, score double")
    )
    place = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(place)).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
