"""Byte-pair encoding: rank-array encoder with decoder (op 10) and heap-based token counter (op 2).

Both read the public vocabulary file given by path and agree with the library's own results.
Both memoise per distinct piece of text, in bounded caches that the tasks of a Python worker share.
"""

from __future__ import annotations

import heapq
import json
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame

from slotlens.llm.common import WordCache, per_worker, slices, text_rows

NO_PAIR = 1 << 40
#: Words above this many bytes take the heap, whose cost is n log n; the scan is quadratic.
SHORT_WORD = 128
#: Words memoised under the pieces that hold them (each at most as long as a short word).
MOST_WORDS = 150_000


def byte_symbols() -> list[str]:
    """Printable stand-in of each byte: itself where printable, else the next code points from 256."""
    printable = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in printable else chr(next(spare)) for b in range(256)]


class Vocabulary:
    """Merge table of a vocabulary file: ``pairs[left << 20 | right] = rank``, ``product[rank] = id``."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.ids: dict[str, int] = spec["model"]["vocab"]
        self.suffix: str = spec["model"].get("end_of_word_suffix") or ""
        self.special: dict[str, int] = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.pairs: dict[int, int] = {}
        self.product: list[int] = []
        for rank, pair in enumerate(spec["model"]["merges"]):
            left, right = pair.split(" ") if isinstance(pair, str) else pair
            self.pairs.setdefault(self.ids[left] << 20 | self.ids[right], rank)
            self.product.append(self.ids[left + right])
        symbols = byte_symbols()
        self.first = [self.ids[s] for s in symbols]
        self.last = [self.ids[s + self.suffix] for s in symbols]
        back = {s: b for b, s in enumerate(symbols)}
        self.bytes_of: dict[int, bytes] = {}
        if not self.suffix:
            self.bytes_of = {i: bytes(back[c] for c in s) for s, i in self.ids.items()}
        self.bytes_of |= {i: s.encode() for s, i in self.special.items()}
        self.cut = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")")

    def symbols(self, word: bytes) -> list[int]:
        out = [self.first[b] for b in word]
        if self.suffix:
            out[-1] = self.last[word[-1]]
        return out


def merge_by_scan(ids: list[int], v: Vocabulary) -> list[int]:
    """Contiguous arrays of parts and of adjacent ranks; scan for the least, drop a boundary, refresh both sides."""
    pairs, product = v.pairs.get, v.product
    ranks = [pairs(a << 20 | b, NO_PAIR) for a, b in zip(ids, ids[1:], strict=False)]
    while ranks:
        least = min(ranks)
        if least == NO_PAIR:
            break
        i = ranks.index(least)
        ids[i] = product[least]
        del ids[i + 1], ranks[i]
        if i:
            ranks[i - 1] = pairs(ids[i - 1] << 20 | ids[i], NO_PAIR)
        if i < len(ranks):
            ranks[i] = pairs(ids[i] << 20 | ids[i + 1], NO_PAIR)
    return ids


def merge_by_heap(ids: list[int], v: Vocabulary) -> int:
    """Pop the lowest-rank adjacent pair from a heap over a linked list; returns the number of merges.

    ``ids`` is left with the merged symbol at each surviving position and -1 elsewhere.
    """
    pairs, product, n = v.pairs, v.product, len(ids)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [pairs[k] << 32 | i for i in range(n - 1) if (k := ids[i] << 20 | ids[i + 1]) in pairs]
    heapq.heapify(heap)
    merges = 0
    while heap:
        rank, i = divmod(heapq.heappop(heap), 1 << 32)
        j = after[i]
        if ids[i] < 0 or j >= n or pairs.get(ids[i] << 20 | ids[j]) != rank:
            continue  # an entry that an earlier merge made stale
        ids[i], ids[j] = product[rank], -1
        merges += 1
        k = after[i] = after[j]
        if k < n:
            before[k] = i
            if (r := pairs.get(ids[i] << 20 | ids[k])) is not None:
                heapq.heappush(heap, r << 32 | i)
        if (h := before[i]) >= 0 and (r := pairs.get(ids[h] << 20 | ids[i])) is not None:
            heapq.heappush(heap, r << 32 | h)
    return merges


class Encoder:
    """Byte-level encoder and decoder over one vocabulary file."""

    #: Fixed value: the pre-tokenizer's pattern.
    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

    def __init__(self, path: str):
        self.v = Vocabulary(path)
        self.find = regex.compile(self.PATTERN).findall
        self.words: dict[str, bytes] = {}
        self.rest = WordCache(lambda ws: [(ws, [self.exact(" " + w) for w in ws])])

    def word(self, w: str) -> bytes:
        found = self.words.get(w)
        if found is None:
            ids = self.v.symbols(w.encode())
            if len(ids) <= SHORT_WORD:
                ids = merge_by_scan(ids, self.v)
            else:
                merge_by_heap(ids, self.v)
                ids = [i for i in ids if i >= 0]
            found = np.array(ids, "<u4").tobytes()
            if len(self.words) >= MOST_WORDS:
                self.words.clear()
            if len(w) <= SHORT_WORD:
                self.words[w] = found
        return found

    def exact(self, text: str) -> bytes:
        out = []
        for k, part in enumerate(self.v.cut.split(text) if "<|" in text else [text]):
            if k % 2:
                out.append(self.v.special[part].to_bytes(4, "little"))
            else:
                out += map(self.word, self.find(part))
        return b"".join(out)

    def encode_all(self, texts: list[str]) -> Iterator[bytes]:
        """Little-endian 32-bit ids of each text."""
        cut = [t.split(" ") for t in texts]
        heads = [c.pop(0) for c in cut]
        for text, head, tail in zip(texts, heads, self.rest.rows(cut), strict=True):
            if tail is None or head and head[-1].isspace():
                yield self.exact(text)
            else:
                yield b"".join([self.exact(head), *tail])

    def decode(self, ids: bytes) -> str:
        get = self.v.bytes_of.__getitem__
        return b"".join(map(get, np.frombuffer(ids, "<u4").tolist())).decode("utf-8", "replace")


class Counter:
    """Token counts of the lower-casing word vocabulary: initial symbols minus heap merges, no ids kept."""

    #: Fixed value: the pre-tokenizer's pattern.
    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"

    def __init__(self, path: str):
        self.v = Vocabulary(path)
        self.find = regex.compile(self.PATTERN).findall
        self.words: dict[str, int] = {}
        self.pieces = WordCache(lambda ws: [(ws, [self.exact(w) for w in ws])])

    def word(self, w: str) -> int:
        found = self.words.get(w)
        if found is None:
            symbols = self.v.symbols(w.encode())
            found = len(symbols) - merge_by_heap(symbols, self.v)
            if len(self.words) >= MOST_WORDS:
                self.words.clear()
            if len(w) <= SHORT_WORD:
                self.words[w] = found
        return found

    def exact(self, text: str) -> int:
        if "<|" in text:
            parts = self.v.cut.split(text)
            return len(parts) // 2 + sum(self.plain(p) for p in parts[::2])
        return self.plain(text)

    def plain(self, text: str) -> int:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
        # Lower-casing goes character by character: no context rule for a final sigma.
        text = "".join(c.lower() for c in text) if "Σ" in text else text.lower()
        return sum(map(self.word, self.find(text)))

    def count_all(self, texts: list[str]) -> Iterator[int]:
        cut = [t.split(" ") for t in texts]
        for text, found in zip(texts, self.pieces.rows(cut), strict=True):
            yield self.exact(text) if found is None else sum(found)


def token_counts(docs: DataFrame, vocabulary: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens of every text, by heap-and-linked-list merging.

    No shuffle: one narrow pass. Null text counts as empty (0 bytes, 0 tokens); null or repeated ids,
    repeated rows and extra columns are carried through as rows; an empty table gives an empty result.
    """

    def run(batches):
        count = per_worker(Counter, vocabulary)
        for batch, texts in slices(batches):
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    pc.cast(pc.binary_length(batch.column("text")), pa.int64()),
                    pa.array(list(count.count_all(texts)), pa.int64()),
                ],
                ["doc_id", "n_bytes", "n_tokens"],
            )

    return text_rows(docs, doc_id=doc_id, text=text).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long")


def encode(docs: DataFrame, vocabulary: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, ids array<int>, decoded string: each whole text encoded by the rank array and decoded again.

    Null text encodes as empty (no ids). Special strings in a text become their ids, as in the library.
    """

    def run(batches):
        codec = per_worker(Encoder, vocabulary)
        for batch, texts in slices(batches):
            ids = list(codec.encode_all(texts))
            flat = np.frombuffer(b"".join(ids), "<i4")
            offsets = np.zeros(len(ids) + 1, np.int32)
            np.cumsum([len(i) // 4 for i in ids], out=offsets[1:])
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat)),
                    pa.array([codec.decode(i) for i in ids], pa.string()),
                ],
                ["doc_id", "ids", "decoded"],
            )

    return text_rows(docs, doc_id=doc_id, text=text).mapInArrow(run, "doc_id long, ids array<int>, decoded string")


def encode_digests(docs: DataFrame, vocabulary: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """As ``encode``, but each row is reduced to n_tokens and two SHA-256 digests inside the worker."""
    from hashlib import sha256

    def run(batches):
        codec = per_worker(Encoder, vocabulary)
        for batch, texts in slices(batches):
            rows = [
                (len(i) // 4, sha256(i).hexdigest(), sha256(codec.decode(i).encode()).hexdigest())
                for i in codec.encode_all(texts)
            ]
            n, ids, decoded = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids), pa.array(decoded)],
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    return text_rows(docs, doc_id=doc_id, text=text).mapInArrow(
        run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    )
