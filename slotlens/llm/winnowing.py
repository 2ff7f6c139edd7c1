"""Winnowed fingerprints of whole texts (op 8)."""

from __future__ import annotations

from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slotlens.llm.common import materialise, text_rows

#: Grams and windows of 8 at every length of text: any common passage of 15 characters is sure to share a fingerprint.
GRAM, WINDOW = 8, 8
#: Characters hashed at once; longer texts go in overlapping runs.
RUN = 1 << 20

BASE = np.uint64(0x9E3779B97F4A7C15)
#: Bytes of text per block of the pass that pairs each text with the next one, and keys drawn per block.
BLOCK_BYTES, DRAWS = 4 << 20, 32


def _powers(n: int) -> np.ndarray:
    out = np.full(n, BASE, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


class Winnower:
    """Rolling gram hashes and the minimum of each window, rightmost among equals."""

    def __init__(self, gram: int = GRAM, window: int = WINDOW):
        self.gram, self.window = gram, window
        inverse = np.uint64(pow(int(BASE), -1, 1 << 64))
        back = np.full(RUN + gram + window + 1, inverse, np.uint64)
        back[0] = 1
        self.up, self.down = _powers(len(back)), np.multiply.accumulate(back)

    def hashes(self, points: np.ndarray) -> np.ndarray:
        """32-bit hash of each gram from prefix sums modulo 2**64, one multiplication to align each."""
        n, k = len(points), min(self.gram, len(points))
        sums = np.empty(n + 1, np.uint64)
        sums[0] = 0
        np.cumsum((points.astype(np.uint64) + np.uint64(1)) * self.up[:n], out=sums[1:])
        h = (sums[k:] - sums[: n - k + 1]) * self.down[: n - k + 1]
        h ^= h >> np.uint64(31)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        return h >> np.uint64(32)

    def _run(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        low = np.uint64(0xFFFFFFFF)
        h = self.hashes(points)
        h = (h << np.uint64(32)) | (low - np.arange(len(h), dtype=np.uint64))
        width, w = 1, min(self.window, len(h))
        while width < w:  # doubling: the least of w grams by log w passes
            step = min(width, w - width)
            h = np.minimum(h[: len(h) - step], h[step:])
            width += step
        keep = np.ones(len(h), bool)
        keep[1:] = h[1:] != h[:-1]
        h = h[keep]
        return (h >> np.uint64(32)).astype(np.uint32), (low - (h & low)).astype(np.int64)

    def fingerprint(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hashes and their gram positions, in order. A text under one gram has one hash of the whole; an empty one none."""
        if not len(points):
            return np.empty(0, np.uint32), np.empty(0, np.int64)
        found, step = [], RUN
        for at in range(0, max(1, len(points) - self.gram - self.window + 2), step):
            h, p = self._run(points[at : at + step + self.gram + self.window - 2])
            p = p + at
            if found and len(found[-1][1]):
                fresh = p > found[-1][1][-1]
                h, p = h[fresh], p[fresh]
            found.append((h, p))
        return np.concatenate([x[0] for x in found]), np.concatenate([x[1] for x in found])


def points_of(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), np.uint32)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard likeness of two hash sets; two empty fingerprints are alike."""
    a, b = np.unique(a), np.unique(b)
    both = len(np.intersect1d(a, b, assume_unique=True))
    union = len(a) + len(b) - both
    return both / union if union else 1.0


def fingerprints(
    docs: DataFrame, gram: int = GRAM, window: int = WINDOW, doc_id: str = "doc_id", text: str = "text"
) -> DataFrame:
    """doc_id, hashes array<long>, positions array<int>: one narrow pass, positions counted in code points.

    Null text is empty: no hashes. Texts under one gram carry one hash of all they hold. Repeated rows repeat.
    """

    def run(batches):
        w = Winnower(gram, window)
        for batch in batches:
            found = [w.fingerprint(points_of(t)) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    pa.array([h.astype(np.int64) for h, _ in found], pa.list_(pa.int64())),
                    pa.array([p.astype(np.int32) for _, p in found], pa.list_(pa.int32())),
                ],
                ["doc_id", "hashes", "positions"],
            )

    return text_rows(docs, doc_id=doc_id, text=text).mapInArrow(
        run, "doc_id long, hashes array<long>, positions array<int>"
    )


def _cuts(keys: DataFrame, blocks: int, total: int) -> tuple[list, DataFrame]:
    """Bounds of about equal bytes: a short list of coarse ones, and a table (coarse, cuts) of the fine ones between them.

    Keys are drawn in proportion to bytes by a fixed hash of the key, ``DRAWS`` a block. Only every so many of them
    come to the driver, about sqrt(blocks) for the coarse bounds.
    """
    chance = F.pmod(F.xxhash64(F.lit(8), "known", "id", "tie"), F.lit(1 << 30)) / float(1 << 30)
    times = F.floor(F.col("bytes") * (DRAWS * blocks / total) + chance).cast("int")
    drawn = materialise(keys.select("key", F.explode(F.array_repeat(F.lit(0), times))).select("key"))
    coarse = int(blocks**0.5)
    few = drawn.where(F.pmod(F.xxhash64(F.lit(9), "key"), F.lit(max(1, DRAWS * blocks // (100 * coarse)))) == 0)
    few = sorted(tuple(r.key) for r in few.collect())
    bounds = sorted({few[i * len(few) // coarse] for i in range(1, coarse)}) if few else []
    held = F.sort_array(F.collect_list("key"))
    table = drawn.groupBy(_below(bounds).alias("coarse")).agg(held.alias("keys"))
    cuts = F.array_distinct(F.filter("keys", lambda _, i: (i > 0) & (i % DRAWS == 0)))
    return bounds, materialise(table.select("coarse", cuts.alias("cuts")))


def _below(bounds: list[tuple[int, int, int]]):
    """How many of the bounds lie below the key."""
    if not bounds:
        return F.lit(0)
    names = ("known", "id", "tie")
    kinds = ("int", "long", "long")
    literal = [F.struct(*(F.lit(x).cast(t).alias(n) for x, t, n in zip(b, kinds, names, strict=True))) for b in bounds]
    return F.size(F.filter(F.array(*literal), lambda c: c < F.col("key")))


def with_next(rows: DataFrame) -> DataFrame:
    """Deals (doc_id, text) into blocks of neighbouring keys, (coarse, fine); each also gets the head of the block after it.

    A key is (whether there is an id, the id, a hash of the text): null ids and repeated ids spread like others, and
    only rows that repeat both id and text stay together. Blocks have about ``BLOCK_BYTES`` each. The heads are one key
    a block: they find their block's borrower in a small table, which is all that is broadcast beside the cuts.
    """
    tie = F.xxhash64("text")
    rows = rows.withColumn("known", F.col("doc_id").isNotNull().cast("int")).withColumn("tie", tie)
    rows = rows.withColumn("key", F.struct("known", F.coalesce("doc_id", F.lit(0).cast("long")).alias("id"), "tie"))
    keys = materialise(rows.select("key", "key.*", (F.octet_length("text") + 1).alias("bytes")))
    total = keys.agg(F.sum("bytes")).first()[0] or 0
    blocks = max(1, -(-total // BLOCK_BYTES))
    if blocks == 1:
        place = [F.lit(0).alias("coarse"), F.lit(0).alias("fine")]
    else:
        bounds, cuts = _cuts(keys, blocks, total)
        fine = F.coalesce(F.size(F.filter("cuts", lambda c: c < F.col("key"))), F.lit(0))
        place = ["coarse", fine.alias("fine")]

        def dealt(df: DataFrame) -> DataFrame:
            named = df.withColumn("coarse", _below(bounds))
            return named.join(F.broadcast(cuts), "coarse", "left")  # about one key a block

        keys, rows = dealt(keys), dealt(rows)
    block = F.struct("coarse", "fine")
    heads = materialise(keys.select("key", *place).groupBy("coarse", "fine").agg(F.max("key").alias("head")))
    upward = Window.orderBy("coarse", "fine")
    # After the last block comes the first: its head is the next document of the very last one.
    borrower = F.coalesce(F.lead(block).over(upward), F.first(block).over(upward))
    guests = heads.select("head", borrower.alias("to"))
    rows = rows.select("doc_id", "text", "key", *place)
    own = rows.select("coarse", "fine", "key", "text", F.lit(False).alias("guest"))
    lent = rows.join(F.broadcast(guests), F.col("key") == F.col("head")).dropDuplicates(["key", "to"])
    lent = lent.select("to.coarse", "to.fine", "key", "text", F.lit(True).alias("guest"))
    return own.unionByName(lent)


def neighbour_edits(
    docs: DataFrame, gram: int = GRAM, window: int = WINDOW, doc_id: str = "doc_id", text: str = "text"
) -> DataFrame:
    """Fingerprints of each text and of its edited text, with likenesses to that and to the next document.

    The next document is the one that follows in descending (doc_id, hash of the text), null ids last, the first
    after the last. Edited: the last floor(n / 2) code points give way to the first as many of the next text.
    A single document is its own neighbour. Null text is empty; an empty table gives an empty result; repeated rows
    are each other's neighbours; other columns are left behind. positions and edited_positions are the grams' first
    code points, one for each eight hexadecimal digits of the fingerprint. One shuffle of the texts, by ranges of the
    key; a block is bounded by bytes, so no task grows with the input.
    """
    rows = text_rows(docs, doc_id=doc_id, text=text)

    def run(table: pa.Table) -> pa.Table:
        w = Winnower(gram, window)
        keys, guest = table.column("key").to_pylist(), table.column("guest").to_pylist()
        order = sorted(range(len(keys)), key=lambda i: (guest[i], *(-keys[i][n] for n in ("known", "id", "tie"))))
        texts, out, later, later_print = table.column("text"), [], None, None
        # From the last to the first: the next text is then at hand, its fingerprint too.
        for i in reversed(order):
            raw = texts[i].as_py().encode("utf-32-le")
            points = np.frombuffer(raw, np.uint32)
            mine, at = w.fingerprint(points)
            if not guest[i]:
                half = len(points) // 2
                edited = np.concatenate([points[: len(points) - half], later[:half]])
                theirs, there = w.fingerprint(edited)
                digest = sha256(edited.tobytes().decode("utf-32-le").encode()).hexdigest()
                prints = (mine.astype(">u4").tobytes().hex(), theirs.astype(">u4").tobytes().hex())
                near = (likeness(mine, theirs), likeness(mine, later_print))
                who = keys[i]["id"] if keys[i]["known"] else None
                out.append((who, len(points), digest, *prints, *near, at.astype(np.int32), there.astype(np.int32)))
            later, later_print = points, mine
        columns = list(zip(*out, strict=True)) or [[]] * 9
        return pa.table([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names)

    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "positions", "edited_positions"]
    places = pa.list_(pa.int32())
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64(), places, places]
    schema = (
        "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, "
        "near_edited double, near_next double, positions array<int>, edited_positions array<int>"
    )
    return with_next(rows).groupBy("coarse", "fine").applyInArrow(run, schema)
