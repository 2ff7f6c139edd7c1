"""Helpers shared by the operators: shared storage, document projection, Arrow loops."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of memoised pieces in one Python worker.
CACHE_BYTES = 64 << 20
#: Rows of a few longs each that may be broadcast.
BROADCAST_ROWS = 500_000


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share; an own temporary one only where none is set and all runs in one process."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get()
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    own = f"file://{tempfile.mkdtemp(prefix='slotlens-')}"
    spark.sparkContext.setCheckpointDir(own)
    return own


@contextmanager
def tidy(spark: SparkSession):
    """Shuffle files of a finished write go at once: every later step reads the written table, not the shuffle."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    old = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if old is None else spark.conf.set(name, old)


def materialise(df: DataFrame) -> DataFrame:
    """Write once to the shared folder and read back: cuts lineage and survives lost executors.

    Parquet keeps later reads column-pruned, which ``checkpoint()`` would not.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/slotlens/{uuid.uuid4().hex}"
    with tidy(spark):
        df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def forget(*tables: DataFrame) -> None:
    """Deletes tables of ``materialise`` that no later step reads."""
    for df in tables:
        jvm = df.sparkSession._jvm
        for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            path = jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def small(df: DataFrame, rows: int | None = None) -> DataFrame:
    """``df`` marked for broadcast if its rows, counted here or known to the caller, are few; else as it is."""
    return F.broadcast(df) if (df.count() if rows is None else rows) <= BROADCAST_ROWS else df


def text_rows(docs: DataFrame, *more: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, text, more...) with a null text read as empty; every other column is left behind."""
    return docs.select(
        F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"), *more
    )


def slices(batches: Iterator[pa.RecordBatch], chars: int = 1_000_000) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Arrow batches cut so that the Python strings alive at once stay near ``chars``.

    At the end of a task freed memory goes back to the system, as the idle worker would keep it from the next stage.
    """
    try:
        for batch in batches:
            lengths = pc.binary_length(batch.column("text")).to_pylist()
            start = held = 0
            for i, n in enumerate(lengths):
                held += n
                if held >= chars or i + 1 == len(lengths):
                    part = batch.slice(start, i + 1 - start)
                    yield part, part.column("text").to_pylist()
                    start, held = i + 1, 0
    finally:
        for pool in (pa.default_memory_pool(), pa.system_memory_pool()):
            pool.release_unused()


def crc_remainder(column: str = "doc_id", modulus: int = 5):
    """crc32 of the id as text, modulo; a null id counts as an empty text."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit(""))) % modulus


def count_below(column, cuts: list[int]):
    """How many of the sorted cuts lie below a value: two levels of about sqrt(n) comparisons each."""
    if not cuts:
        return F.lit(0)
    width = int(len(cuts) ** 0.5) + 1
    groups = [cuts[i : i + width] for i in range(0, len(cuts), width)]
    upper = F.size(F.filter(F.array(*(F.lit(g[-1]) for g in groups)), lambda c: c < column))
    lower = F.array(*(F.array(*map(F.lit, g)) for g in groups))
    inner = F.size(F.filter(F.get(lower, upper), lambda c: c < column))
    return F.when(upper >= len(groups), len(cuts)).otherwise(upper * width + inner)


def literal_table(spark: SparkSession, columns: dict[str, tuple[str, list]]) -> DataFrame:
    """Small table from driver-side lists, as one generated row source without Python on the executors."""
    zipped = F.arrays_zip(*(F.array(*map(F.lit, v)).cast(f"array<{t}>").alias(n) for n, (t, v) in columns.items()))
    return spark.range(1, numPartitions=1).select(F.inline(zipped))


class WordCache:
    """Memo of pieces between single spaces, bounded by bytes, in two generations.

    When the young generation has half of the budget it becomes the old one, whose entries come back as they are
    met again: hot pieces stay, rare ones go. ``many`` takes new pieces and yields them with their values, in runs. A
    piece that is empty or that touches white space at an edge depends on its neighbours and is never held: the
    whole text then takes the caller's exact route.
    """

    def __init__(self, many: Callable[[list[str]], Iterator[tuple[list, list]]], budget: int = CACHE_BYTES):
        self.many, self.budget = many, budget
        self.young, self.old, self.held = {}, {}, 0

    def rows(self, rows: list[list[str]]) -> list[list | None]:
        """The values of each row's pieces; None for a row with a piece that depends on its neighbours."""
        if self.held > self.budget // 2:
            self.young, self.old, self.held = {}, self.young, 0
        get = self.young.get
        out = [list(map(get, row)) for row in rows]
        gaps = [(k, [i for i, v in enumerate(found) if v is None]) for k, found in enumerate(out) if None in found]
        self.learn({rows[k][i] for k, at in gaps for i in at})
        for k, at in gaps:
            found, row = out[k], rows[k]
            for i in at:
                found[i] = get(row[i])
            if None in found:
                out[k] = None
        return out

    def learn(self, new: set[str]) -> None:
        young, old = self.young, self.old
        if old and new:
            fresh = new.difference(old)
            again = list(new - fresh)
            young.update(zip(again, map(old.__getitem__, again), strict=True))
            self.held += _weight(again)
            new = fresh
        new = [w for w in new if w and w.strip() == w]
        for keys, values in self.many(new):
            young.update(zip(keys, values, strict=True))
        self.held += _weight(new)


def _weight(words: list[str]) -> int:
    """Bytes of a dictionary's entries with these keys, values of about their size included."""
    return 130 * len(words) + 4 * sum(map(len, words))


_held: dict[tuple, object] = {}


def per_worker(kind: Callable, *arguments):
    """One object for all tasks of a Python worker. Only the last kind asked for is held, so that the caches of one
    operator are gone before the next one builds its own."""
    key = (kind, *arguments)
    if key not in _held:
        _held.clear()
        gc.collect()
        _held[key] = kind(*arguments)
    return _held[key]
