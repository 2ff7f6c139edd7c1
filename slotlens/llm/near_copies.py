"""Jaccard self-join over word shingles by a MinHash LSH forest with exact verification (op 6)."""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import blake2b
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slotlens.llm.common import forget, materialise, per_worker, slices, small
from slotlens.llm.components import components

SHINGLE, LEAST_LIKENESS = 5, 0.8
#: Trees of the forest, levels of each, and the recall at which prefixes are no longer shortened.
TREES, DEPTH, TARGET = 24, 8, 0.9999
#: Distinct sets, and bytes of them, in one block of a verification task.
BLOCK, BLOCK_BYTES = 512, 4 << 20
#: A candidate component of more blocks than this is verified prefix by prefix.
WIDE = 8


def shares_prefix(likeness, length: int, trees: int = TREES):
    """Chance that two sets of a likeness share a prefix of a length in some tree."""
    return 1 - (1 - np.asarray(likeness, float) ** length) ** trees


def shortest_prefix(threshold: float = LEAST_LIKENESS, trees: int = TREES, depth: int = DEPTH, target: float = TARGET) -> int:
    """The length below which no prefix need be shortened: even pairs at the threshold then meet the target."""
    return next((d for d in range(depth, 1, -1) if shares_prefix(threshold, d, trees) >= target), 1)


#: White space, by code point; none lies beyond the last entry.
BLANK = np.array([chr(c).isspace() for c in range(0x3001)] + [False])
#: Characters hashed at once; a longer text is cut between words.
RUN = 1 << 19
BASE = 0x9E3779B97F4A7C15


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


def _mix(h: np.ndarray, shift: int) -> np.ndarray:
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(shift)
    return h


class Sketcher:
    """Shingle sets and their paths in the trees of the forest."""

    def __init__(self, shingle: int = SHINGLE, trees: int = TREES, depth: int = DEPTH):
        self.shingle, self.trees, self.depth = shingle, trees, depth
        bins = trees * depth
        # Minimum hashes by one permutation: the hash range is cut into one bin a level of a tree.
        self.edges = (np.arange(bins, dtype=np.float64) * (2.0**64 / bins)).astype(np.uint64)
        rng = np.random.default_rng(20_240_501)
        self.turn = np.stack([rng.permutation(bins) for _ in range(bins)])
        self.up, self.down = _powers(BASE, RUN + 1), _powers(pow(BASE, -1, 1 << 64), RUN + 1)

    def words(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """64-bit hash of each run between white space, and where it starts: a polynomial of its code points."""
        if len(points) >= len(self.up):  # one word longer than a run
            self.up, self.down = _powers(BASE, len(points) + 1), _powers(pow(BASE, -1, 1 << 64), len(points) + 1)
        blank = BLANK[np.minimum(points, len(BLANK) - 1)]
        edge = np.flatnonzero(np.diff(blank, prepend=True, append=True))
        starts, ends = edge[::2], edge[1::2]
        sums = np.empty(len(points) + 1, np.uint64)
        sums[0] = 0
        np.cumsum(_mix(points + np.uint64(BASE), 32) * self.up[: len(points)], out=sums[1:])
        return _mix(_mix((sums[ends] - sums[starts]) * self.down[starts], 31), 29), starts

    def runs(self, points: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """``words`` over runs of bounded length, cut at white space."""
        at = 0
        while at < len(points):
            end = at + RUN
            if end < len(points):
                gaps = np.flatnonzero(BLANK[np.minimum(points[at:end], len(BLANK) - 1)])
                if len(gaps):
                    end = at + int(gaps[-1]) + 1
                else:
                    while end < len(points) and not BLANK[min(int(points[end]), len(BLANK) - 1)]:
                        end += 1
            w, starts = self.words(points[at:end])
            yield w, starts + at
            at = end

    def sets(self, texts: list[str]) -> list[np.ndarray]:
        """Sorted distinct 64-bit hashes of the word runs; fewer words than a run make one run, none an empty set."""
        points = np.frombuffer("\n".join(texts).encode("utf-32-le"), np.uint32)
        found = list(self.runs(points)) or [(np.empty(0, np.uint64), np.empty(0, np.int64))]
        w, starts = (np.concatenate(x) for x in zip(*found, strict=True))
        bounds = np.searchsorted(starts, np.cumsum([0, *(len(t) + 1 for t in texts)]))
        grams, k = self.grams(w, self.shingle), self.shingle
        return [
            np.unique(grams[a : b - k + 1]) if b - a >= k else self.grams(w[a:b], b - a) for a, b in pairwise(bounds.tolist())
        ]

    @staticmethod
    def grams(w: np.ndarray, k: int) -> np.ndarray:
        n = len(w) - k + 1 if k else 0
        h = np.full(max(n, 0), k, np.uint64)
        for i in range(k if n > 0 else 0):
            h ^= w[i : i + n]
            _mix(h, 29)
        return h

    def paths(self, s: np.ndarray) -> np.ndarray:
        """trees x depth 16-bit minimum hashes: the path of the set in each tree, as bytes that sort like the path.

        The least hash of each bin is its level's value. An empty bin takes the value of the first full one in a
        random order of its own, the same for all sets, so that two sets agree on a level with the chance of their
        likeness however few elements they have.
        """
        if not len(s):
            return np.zeros((self.trees, self.depth), ">u2")
        at = np.searchsorted(s, self.edges)
        full = np.diff(at, append=len(s)) > 0
        if not full.all():
            empty = np.flatnonzero(~full)
            turn = self.turn[empty]
            at[empty] = at[turn[np.arange(len(empty)), full[turn].argmax(axis=1)]]
        value = s[at] * np.uint64(0xD6E8FEB86659FD93)
        return (value >> np.uint64(48)).astype(">u2").reshape(self.trees, self.depth)


def sketches(docs: DataFrame, shingle: int, trees: int, depth: int, doc_id: str, text: str) -> DataFrame:
    """doc_id, row_id, text_hash, set_key (digest of the shingle set), shingles (64-bit values as bytes), paths (bytes).

    row_id is the task's number and a count in it: fixed once the rows are written, which the caller does.
    """

    def run(batches: Iterator[pa.RecordBatch]):
        sketch = per_worker(Sketcher, shingle, trees, depth)
        row = TaskContext.get().partitionId() << 36
        for batch, texts in slices(batches, RUN):
            sets = sketch.sets(texts)
            raw = [s.astype("<u8").tobytes() for s in sets]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    pa.array(np.arange(row, row + len(sets))),
                    batch.column("text_hash"),
                    pa.array([blake2b(r, digest_size=16).digest() for r in raw], pa.binary()),
                    pa.array(raw, pa.binary()),
                    pa.array([sketch.paths(s).tobytes() for s in sets], pa.binary()),
                ],
                ["doc_id", "row_id", "text_hash", "set_key", "shingles", "paths"],
            )
            row += len(sets)

    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    rows = rows.withColumn("text_hash", F.xxhash64("text"))
    return rows.mapInArrow(run, "doc_id long, row_id long, text_hash long, set_key binary, shingles binary, paths binary")


def _prefix_ids(paths: np.ndarray, length: int) -> np.ndarray:
    """Number of each row's prefix in each tree, from the sorted prefixes of the tree: rows x trees."""
    out = np.empty(paths.shape[:2], np.int32)
    for t in range(paths.shape[1]):
        sorted_ = np.ascontiguousarray(paths[:, t, :length]).view(f"V{2 * length}").ravel()
        out[:, t] = np.unique(sorted_, return_inverse=True)[1].ravel()
    return out


def candidates(paths: np.ndarray, floor: int, crossing: np.ndarray | None = None, tree: int = -1) -> tuple[np.ndarray, ...]:
    """Pairs i < j that share a prefix of the floor's length, with the longest length they share in any tree.

    ``crossing``: only pairs across these two blocks. ``tree``: only pairs whose first shared prefix is that tree's.
    """
    ids = _prefix_ids(paths, floor)
    n = len(ids)
    left, right, longest = [], [], []
    for at in range(0, n, 256):
        rows = slice(at, min(n, at + 256))
        share = np.zeros((rows.stop - at, n), bool)
        for t in range(ids.shape[1]):
            share |= ids[rows, t, None] == ids[None, :, t]
        share &= np.arange(at, rows.stop)[:, None] < np.arange(n)[None]
        if crossing is not None:
            share &= crossing[rows, None] != crossing[None]
        i, j = np.nonzero(share)
        i += at
        for k in range(0, len(i), 20_000):
            a, b = i[k : k + 20_000], j[k : k + 20_000]
            if tree >= 0:
                mine = (ids[a] == ids[b]).argmax(axis=1) == tree
                a, b = a[mine], b[mine]
            same = np.logical_and.accumulate(paths[a] == paths[b], axis=2)
            left.append(a)
            right.append(b)
            longest.append(same.sum(axis=2).max(axis=1, initial=0))
    if not left:
        return (np.empty(0, np.int64),) * 3
    return np.concatenate(left), np.concatenate(right), np.concatenate(longest)


class Likeness:
    """Exact Jaccard likeness of pairs of sets."""

    def __init__(self, sets: list[np.ndarray]):
        self.lengths = np.array([len(s) for s in sets])
        self.flat = np.unique(np.concatenate(sets), return_inverse=True)[1].ravel()
        self.ends = np.concatenate([[0], self.lengths.cumsum()])
        self.held = np.zeros(int(self.flat.max(initial=-1)) + 1, bool)

    def of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Pairs come sorted by their left row."""
        out = np.empty(len(left))
        rows, starts = np.unique(left, return_index=True)
        for i, (a, b) in zip(rows, pairwise([*starts.tolist(), len(left)]), strict=True):
            mine = self.flat[self.ends[i] : self.ends[i + 1]]
            self.held[mine] = True
            for at in range(a, b, 512):
                part = right[at : min(b, at + 512)]
                sizes = self.lengths[part]
                bounds = np.concatenate([[0], sizes.cumsum()])
                take = np.arange(bounds[-1]) + np.repeat(self.ends[part] - bounds[:-1], sizes)
                both = np.add.reduceat(self.held[self.flat[take]].astype(np.int64), bounds[:-1])
                out[at : at + len(part)] = both / (sizes + self.lengths[i] - both)
            self.held[mine] = False
        return out


def links(sets: list[np.ndarray], paths: np.ndarray, threshold: float, floor: int, target: float, crossing=None, tree: int = -1):
    """Pairs (i, j) of exact likeness at or above the threshold, found by shortening the shared prefixes.

    Pairs that share the longest prefixes are verified first. After each length the recall is estimated from the
    links found so far, each standing for the links of its likeness that share no such prefix, with one more link
    right at the threshold; prefixes are shortened, to the floor at most, until the estimate meets the target.
    """
    left, right, longest = candidates(paths, floor, crossing, tree)
    trees, depth = paths.shape[1:]
    likeness = Likeness(sets)
    small_, large = np.minimum(likeness.lengths[left], likeness.lengths[right]), np.maximum(likeness.lengths[left], likeness.lengths[right])
    # A ratio of sizes below the threshold cannot reach it.
    fit = small_ >= threshold * large - 1e-9
    left, right, longest = left[fit], right[fit], longest[fit]
    found, values = [], [np.array([threshold])]
    for length in range(depth, floor - 1, -1):
        at = np.flatnonzero(longest == length)
        share = likeness.of(left[at], right[at])
        good = share >= threshold - 1e-12
        found.append(at[good])
        values.append(share[good])
        known = np.concatenate(values)
        if len(known) / (1 / shares_prefix(known, length, trees)).sum() >= target:
            break
    at = np.concatenate(found)
    return left[at], right[at]


def _roots(n: int, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Least row of each row's component."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[left], root[right])
        new = root.copy()
        np.minimum.at(new, left, low)
        np.minimum.at(new, right, low)
        np.minimum.at(new, root[left], low)
        np.minimum.at(new, root[right], low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def _blocks(rows: str, size: str):
    return F.greatest(F.ceil(F.col(rows) / F.lit(BLOCK)), F.ceil(F.col(size) / F.lit(BLOCK_BYTES))).cast("int")


def _dealt(members: DataFrame) -> DataFrame:
    """(cell, tree, blocks, node) as (cell, tree, blocks, node, mine, a, b): one task for each pair of blocks of a cell."""
    members = members.withColumn("mine", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    members = members.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    return members.select(
        "cell", "tree", "blocks", "node", "mine", F.least("mine", "other").alias("a"), F.greatest("mine", "other").alias("b")
    )


def _cells(classes: DataFrame, trees: int, depth: int, floor: int) -> DataFrame:
    """The tasks of the verification, as rows of ``_dealt``: classes that share a prefix of the floor's length.

    Classes that prefixes connect are one cell, cut into blocks by hash if it is large; tree is then -1. A component
    of more than ``WIDE`` blocks, as boilerplate may build, would send each of its sets to every block: there each
    bucket of a prefix is a cell of its own, one of several buckets with the same members stands for all, and a
    pair belongs to the first tree in which it shares a prefix.
    """
    prefix = F.explode(
        F.transform(
            F.sequence(F.lit(0), F.lit(trees - 1)),
            lambda t: F.struct(
                t.alias("tree"), F.xxhash64(t, F.substring(F.col("paths"), t * (2 * depth) + 1, F.lit(2 * floor))).alias("prefix")
            ),
        )
    )
    keys = classes.select("node", prefix.alias("k")).select("node", "k.tree", "k.prefix")
    firsts = keys.groupBy("prefix").agg(F.min("node").alias("u"), F.max("node").alias("w"))
    firsts = materialise(firsts.where("u != w").select("prefix", "u"))
    shared = materialise(keys.join(small(firsts), "prefix").select("tree", "prefix", "u", "node"))
    forget(firsts)
    member = materialise(components(shared.where("node != u").select("u", F.col("node").alias("v"))))
    sized = member.join(classes.select("node", "size"), "node")
    groups = sized.groupBy("component").agg(F.count("*").alias("rows"), F.sum("size").alias("size"))
    groups = materialise(groups.select("component", _blocks("rows", "size").alias("blocks")))
    narrow = member.join(small(groups.where(F.col("blocks") <= WIDE)), "component")
    dealt = _dealt(narrow.select(F.col("component").alias("cell"), F.lit(-1).alias("tree"), "blocks", "node"))
    wide = groups.where(F.col("blocks") > WIDE).select("component")
    if not wide.take(1):
        return dealt
    wide_nodes = member.join(small(wide), "component").select("node")
    inside = materialise(shared.join(wide_nodes, "node").join(classes.select("node", "size"), "node"))
    buckets = inside.groupBy("prefix").agg(
        F.min("tree").alias("tree"),
        F.count("*").alias("rows"),
        F.sum("size").alias("size"),
        F.sum(F.xxhash64("node").cast("decimal(38,0)")).alias("who"),
        F.min("node").alias("least"),
    )
    first = F.min(F.struct("tree", "prefix", "size")).alias("first")
    buckets = buckets.groupBy("rows", "who", "least").agg(first).select("rows", "first.*").where("rows > 1")
    buckets = buckets.select("prefix", _blocks("rows", "size").alias("blocks"))
    spread = inside.join(buckets, "prefix").select(F.col("prefix").alias("cell"), "tree", "blocks", "node")
    return dealt.unionByName(_dealt(spread))


def join(docs: DataFrame, **options) -> DataFrame:
    """doc_id, row_id, set_id, class_id, n_links: one row per row of ``docs``.

    set_id is the least doc_id with the same shingle set; class_id the least doc_id that a chain of links of at
    least ``threshold`` reaches; n_links counts the other rows linked to this one, equal sets included. Words are
    runs of characters between white space, case kept; a text of fewer than ``shingle`` words is one shingle, and
    texts without words (null ones too) have the empty set, alike to each other only. Repeated rows are copies.
    Null ids come after all others; a class of null ids alone has a null class_id. Columns other than id and text
    are left behind; an empty table gives an empty result.

    Rows with equal sets collapse to a class before any candidate search, so copies never pair up. Candidates
    share a prefix in some tree of the forest; they are verified on the sets themselves inside tasks of bounded
    size, from the longest shared prefixes to shorter ones (``links``), and what leaves a task is one row a member
    with its count of links, not the pairs.
    """
    return linked(docs, **options).select("doc_id", "row_id", "set_id", "class_id", "n_links")


def linked(
    docs: DataFrame,
    threshold: float = LEAST_LIKENESS,
    shingle: int = SHINGLE,
    trees: int = TREES,
    depth: int = DEPTH,
    target: float = TARGET,
    doc_id: str = "doc_id",
    text: str = "text",
) -> DataFrame:
    """As ``join``, with text_hash (of the row's text) and root (the class itself, also where ids are null)."""
    floor = shortest_prefix(threshold, trees, depth, target)
    sketched = materialise(sketches(docs, shingle, trees, depth, doc_id, text))
    classes = sketched.groupBy("set_key").agg(
        F.min("doc_id").alias("set_id"),
        F.count("*").alias("copies"),
        F.min("row_id").alias("node"),
        F.first(F.octet_length("shingles")).alias("size"),
        F.first("paths").alias("paths"),
    )
    classes = materialise(classes)
    cells = materialise(_cells(classes, trees, depth, floor))
    ids = materialise(cells.select("node").distinct())
    few = ids.count()
    # While the ids are few, only the sets that are needed travel.
    sets = sketched.select(F.col("row_id").alias("node"), "shingles").join(small(ids, few), "node", "left_semi")
    wanted = classes.join(small(ids, few), "node", "left_semi").select("node", "copies", "paths")
    loaded = cells.join(sets.join(wanted, "node"), "node")

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("node")
        # In a cell of two blocks only pairs across them count: those inside a block are its own cell's.
        crossing = table.column("mine").to_numpy() if table.column("a")[0] != table.column("b")[0] else None
        found = [np.frombuffer(x.as_py(), "<u8") for x in table.column("shingles")]
        paths = np.frombuffer(b"".join(table.column("paths").to_pylist()), ">u2").reshape(-1, trees, depth)
        left, right = links(found, paths, threshold, floor, target, crossing, table.column("tree")[0].as_py())
        copies = table.column("copies").to_numpy()
        count = np.bincount(left, copies[right], len(found)) + np.bincount(right, copies[left], len(found))
        root = table.column("node").take(pa.array(_roots(len(found), left, right)))
        whole = pa.array(np.full(len(found), table.column("blocks")[0].as_py() == 1 and table.column("tree")[0].as_py() < 0))
        return pa.table({"node": table.column("node"), "root": root, "links": pa.array(count.astype(np.int64)), "whole": whole})

    local = materialise(
        loaded.groupBy("cell", "tree", "a", "b").applyInArrow(run, "node long, root long, links long, whole boolean")
    )
    forget(cells, ids)
    # A component verified in one task: its roots are final. Others: roots are edges of the group's own small graph.
    merged = local.where("whole").select("node", "root")
    spread = local.where("not whole and node != root").select(F.col("node").alias("u"), F.col("root").alias("v"))
    if spread.take(1):
        merged = merged.unionAll(components(spread).select("node", F.col("component").alias("root")))
    count = local.groupBy("node").agg(F.sum("links").alias("links"))
    named = (
        classes.select("set_key", "node", "set_id", "copies")
        .join(small(merged, few), "node", "left")
        .join(small(count, few), "node", "left")
        .withColumn("root", F.coalesce("root", "node"))
    )
    # Only classes that others point to can have another name than their own.
    grouped = named.join(small(merged, few).select("node"), "node", "left_semi")
    least = grouped.groupBy("root").agg(F.min("set_id").alias("least_id"))
    named = named.join(small(least, few), "root", "left").select(
        "set_key",
        "root",
        "set_id",
        F.coalesce("least_id", "set_id").alias("class_id"),
        (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"),
    )
    rows = sketched.select("doc_id", "row_id", "text_hash", "set_key").join(named, "set_key")
    return rows.select("doc_id", "row_id", "text_hash", "root", "set_id", "class_id", "n_links")


def one_of_each(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with one row kept of each class: the one of least id (then least hash of the text); columns as they were.

    Only (id, hash of the text) of rows that have links travel to the decision, which an anti join carries out;
    rows that repeat an id and a text are told apart only where there are any.
    """
    names = docs.columns
    body = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(
        F.struct(*names).alias("_row"), F.col("doc_id").cast("long").alias("_id"), F.xxhash64(body).alias("_hash")
    )
    found = materialise(linked(docs, **options).where("n_links > 0").select("root", "doc_id", "text_hash"))
    mark = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_hash")
    kept = found.groupBy("root").agg(F.min(mark).alias("kept"))
    gone = materialise(found.join(kept, "root").where(~mark.eqNullSafe(F.col("kept"))).select("doc_id", "text_hash").distinct())
    gone = small(gone)

    def same(keys: DataFrame):
        return rows["_id"].eqNullSafe(keys["doc_id"]) & (rows["_hash"] == keys["text_hash"])

    left = rows.join(gone, same(gone), "left_anti")
    again = materialise(found.groupBy("doc_id", "text_hash").count().where("count > 1").select("doc_id", "text_hash"))
    if again.take(1):
        once = left.join(again, same(again), "left_semi").dropDuplicates(["_id", "_hash"])
        left = left.join(again, same(again), "left_anti").unionAll(once)
    return left.select("_row.*")
