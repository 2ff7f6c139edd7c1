"""Sum-of-squares packing of tokenised documents into fixed-length sequences (op 4)."""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slotlens.llm.common import WordCache, materialise, per_worker, slices, text_rows

SEQUENCE, END_ID = 1024, 2
#: Pieces packed together in one task: enough for waste below a percent, small enough for any worker.
PER_GROUP = 40_000
#: Fixed value: what the vocabulary writes for a space.
SPACE = "\u0120"


class LibraryIds:
    """Ids by the tokenizers library; pieces between single spaces are looked up once per worker."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.rest = WordCache(self.after_space)
        self.starts = np.zeros(self.library.get_vocab_size(), bool)
        for token, i in self.library.get_vocab().items():
            self.starts[i] = token.startswith(SPACE)

    def batch(self, texts: list[str]) -> list[bytes]:
        out = []
        for at in range(0, len(texts), 4096):
            found = self.library.encode_batch_fast(texts[at : at + 4096], add_special_tokens=False)
            out += [np.array(e.ids, "<u4").tobytes() for e in found]
        return out

    def after_space(self, words: list[str]) -> Iterator[tuple[list[str], list[bytes]]]:
        """Ids of each word with a space before it. Words go many to a call, joined by spaces: none has a space or an
        edge of white space, so each space begins a token, and only such tokens begin a word. Words that may hold a
        special string go alone, as does a run in which the count does not come out."""
        rest = [w for w in words if "<" in w]
        plain = [w for w in words if "<" not in w] if rest else words
        for at in range(0, len(plain), 128):
            part = plain[at : at + 128]
            ids = np.array(self.library.encode_batch_fast([" " + " ".join(part)], add_special_tokens=False)[0].ids, "<u4")
            cut = (4 * np.flatnonzero(self.starts[ids])).tolist()
            if len(cut) != len(part):
                rest += part
                continue
            raw = ids.tobytes()
            cut.append(len(raw))
            yield part, [raw[a:b] for a, b in pairwise(cut)]
        yield rest, self.batch([" " + w for w in rest])

    def of(self, texts: list[str]) -> list[bytes]:
        cut = [t.split(" ") for t in texts]
        heads = [c.pop(0) for c in cut]
        tails, whole = self.rest.rows(cut), []
        for k, tail in enumerate(tails):
            if tail is None or heads[k] and heads[k][-1].isspace():
                whole.append(k)  # a piece that depends on its neighbours: the whole text goes to the library
                tails[k] = None
        first = self.batch(heads)
        full = dict(zip(whole, self.batch([texts[k] for k in whole]), strict=True))
        return [full[k] if tail is None else b"".join([first[k], *tail]) for k, tail in enumerate(tails)]


def pieces(
    docs: DataFrame,
    vocabulary: str,
    length: int = SEQUENCE,
    end_id: int = END_ID,
    with_ids: bool = True,
    doc_id: str = "doc_id",
    text: str = "text",
) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and ids): every document's tokens plus the end id, cut only if longer.

    The first piece takes the remainder, so that all later ones are full. Null text is empty and yields the end id.
    """

    def run(batches):
        ids_of = per_worker(LibraryIds, vocabulary)
        end = np.array([end_id], "<u4").tobytes()
        for batch, texts in slices(batches):
            who, number, start, n, crc, ids = [], [], [], [], [], []
            for k, raw in enumerate(ids_of.of(texts)):
                raw += end
                total = len(raw) // 4
                at, size, i = 0, total % length or length, 0
                while at < total:
                    part = raw[4 * at : 4 * (at + size)]
                    who.append(k)
                    number.append(i)
                    start.append(at)
                    n.append(size)
                    crc.append(zlib.crc32(part))
                    ids.append(part)
                    at, size, i = at + size, length, i + 1
            columns = [
                batch.column("doc_id").take(pa.array(who, pa.int64())),
                pa.array(number, pa.int32()),
                pa.array(start, pa.int64()),
                pa.array(n, pa.int64()),
                pa.array(crc, pa.int64()),
            ]
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            if with_ids:
                offsets = np.zeros(len(n) + 1, np.int32)
                np.cumsum(n, out=offsets[1:])
                flat = pa.array(np.frombuffer(b"".join(ids), "<i4"))
                columns.append(pa.ListArray.from_arrays(pa.array(offsets), flat))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names)

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids
    return text_rows(docs, doc_id=doc_id, text=text).mapInArrow(run, schema)


def sum_of_squares(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each size, placed in the order given.

    ``open_[g]`` counts open bins of gap g. Putting s into gap g changes the sum of squares by
    2 (open_[g - s] - open_[g]) + 2, the s = g and new-bin cases lacking one of the two terms;
    the least change wins, the tightest gap among equals.
    """
    open_ = np.zeros(capacity + 1, np.int64)
    stacks: list[list[int]] = [[] for _ in range(capacity + 1)]
    bins, offsets, made = np.empty(len(sizes), np.int64), np.empty(len(sizes), np.int64), 0
    for k, s in enumerate(sizes.tolist()):
        here, left = open_[s:capacity], open_[: capacity - s]
        change = np.where(here > 0, 2 * (left - here) + 2, 1 << 40)
        if s < capacity and here[0]:
            change[0] = 1 - 2 * here[0]
        g = s + int(change.argmin()) if s < capacity else capacity
        fresh = 2 * int(open_[capacity - s]) + 1 if s < capacity else 0
        if s == capacity or change[g - s] > fresh:
            b, g, made = made, capacity, made + 1
        else:
            b = stacks[g].pop()
            open_[g] -= 1
        bins[k], offsets[k] = b, capacity - g
        if g > s:
            stacks[g - s].append(b)
            open_[g - s] += 1
    return bins, offsets


def place(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """The better of two orders for one group: as they come, and large to small."""
    best = None
    for order in (np.arange(len(sizes)), np.argsort(-sizes, kind="stable")):
        bins, offsets = sum_of_squares(sizes[order], capacity)
        if best is None or bins.max() < best[0].max():
            back = np.empty(len(order), np.int64)
            back[order] = np.arange(len(order))
            best = bins[back], offsets[back]
    return best


def pack(cut: DataFrame, capacity: int = SEQUENCE, per_group: int = PER_GROUP) -> DataFrame:
    """Adds sequence_id and offset to rows that have doc_id, piece, start, length, ids_crc32.

    Rows are dealt by hash into groups of about ``per_group``; each group is packed alone by sum of squares,
    which costs at most a few part-filled sequences a group. Copies spread evenly, as the hash covers a row number.
    Rows arrive unordered, so a group sorts them by content before placing: the outcome doesn't depend on task order.
    """
    cut = materialise(cut)
    groups = max(1, -(-cut.count() // per_group))
    names = cut.columns

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by([(c, "ascending") for c in ("ids_crc32", "doc_id", "piece", "length")])
        bins, offsets = place(table.column("length").to_numpy(), capacity)
        base = table.column("group")[0].as_py() << 40
        return table.select(names).append_column("sequence_id", pa.array(bins + base)).append_column(
            "offset", pa.array(offsets)
        )

    key = F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32", F.monotonically_increasing_id()), F.lit(groups))
    schema = ", ".join(f"{n} {t}" for n, t in cut.dtypes) + ", sequence_id long, offset long"
    return cut.withColumn("group", key).groupBy("group").applyInArrow(run, schema)


def sequences(packed: DataFrame) -> DataFrame:
    """The training sequences themselves: sequence_id, ids, from packed pieces that carry ids."""
    parts = F.sort_array(F.collect_list(F.struct("offset", "ids")))
    return packed.groupBy("sequence_id").agg(F.flatten(F.transform(parts, lambda p: p["ids"])).alias("ids"))
