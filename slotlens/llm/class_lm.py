"""Class-based bigram model with exchange clustering, learned from and applied to a whole corpus (op 1)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slotlens.llm.common import crc_remainder, forget, materialise, slices, tidy

#: The start of the clustering: words exchanged one by one and groups of all others by their ending; least classes; sweeps over that table.
HEADS, ENDINGS, CLASSES, SWEEPS = 1500, 500, 48, 4
#: Parallel sweeps over all words that follow.
WORD_SWEEPS = 2
#: Most characters of text per block, and what input splits are joined to; a block's own word list is what a task holds.
#: The rows of (block, word) grow more slowly than a block, so that full blocks shuffle less.
BLOCK_CHARS, FULL_CHARS = 48 << 20, 40 << 20
#: Counts whose gains are looked up in place of computed.
FEW = 8
#: The end of a text in the word list; no word holds white space.
END = b"\n"
PRIOR = 200.0


class Numbering(dict):
    """Word -> number in order of first sight; the end of a text is number 0."""

    def __init__(self):
        super().__init__({END: 0})

    def __missing__(self, word: bytes) -> int:
        self[word] = number = len(self)
        return number


def tokens_of(text: str) -> list[bytes]:
    """Words between blanks, tabs and line breaks of ASCII, with A-Z in lower case."""
    return text.encode().lower().split()


def blocks(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Two kinds of rows: documents as numbers into their block's word list, and the words with training counts."""

    def run(batches):
        part, serial = TaskContext.get().partitionId(), 0
        numbering, rows, held = Numbering(), [], 0

        def flush():
            block = part << 24 | serial
            ids = [r[2] for r in rows]
            train = [i for i, r in zip(ids, rows, strict=True) if not r[1]]
            counts = np.bincount(np.concatenate(train), minlength=len(numbering)) if train else np.zeros(len(numbering), int)
            n, m = len(rows), len(numbering)
            of_texts = {
                "doc_id": pa.array([r[0] for r in rows], pa.int64()),
                "held_out": pa.array([r[1] for r in rows], pa.bool_()),
                "numbers": pa.array([i.tobytes() for i in ids], pa.binary()),
            }
            of_words = {
                "word": pa.array(numbering, pa.binary(), size=m),
                "number": pa.array(np.arange(m, dtype=np.int32)),
                "n_train": pa.array(counts.astype(np.int64)),
            }
            columns = {"block": pa.array(np.full(n + m, block, np.int64))}
            columns |= {name: pa.chunked_array([x, pa.nulls(m, x.type)]) for name, x in of_texts.items()}
            columns |= {name: pa.chunked_array([pa.nulls(n, x.type), x]) for name, x in of_words.items()}
            yield from pa.table(columns).to_batches(max_chunksize=20_000)

        for batch, texts in slices(batches):
            who, out = batch.column("doc_id").to_pylist(), batch.column("held_out").to_pylist()
            for d, h, t in zip(who, out, texts, strict=True):
                words = tokens_of(t)
                words.append(END)
                rows.append((d, h, np.fromiter(map(numbering.__getitem__, words), np.uint32, len(words))))
                held += len(t)
            if held >= BLOCK_CHARS:
                yield from flush()
                numbering, rows, held, serial = Numbering(), [], 0, serial + 1
        if rows:
            yield from flush()

    body = docs.select(
        F.col(doc_id).cast("long").alias("doc_id"),
        (crc_remainder(doc_id) == 1).alias("held_out"),
        F.coalesce(F.col(text), F.lit("")).alias("text"),
    )
    # Small input splits are joined until they fill a block, as long as every core has one.
    chars = body.select(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    tasks = max(-(-chars // FULL_CHARS), docs.sparkSession.sparkContext.defaultParallelism)
    schema = "block long, doc_id long, held_out boolean, numbers binary, word binary, number int, n_train long"
    return body.coalesce(tasks).mapInArrow(run, schema)


def class_count(words: int) -> int:
    """Classes for a vocabulary: they grow with its fourth root, so that the table of class pairs grows with the square root."""
    return max(CLASSES, round(1.2 * words**0.25))


def exchange(pairs: np.ndarray, fixed: int, classes: int, sweeps: int = SWEEPS) -> np.ndarray:
    """Class of each item by exchange: each item in turn moves where the bigram likelihood gains most.

    ``pairs[a, b]`` counts b after a. Item ``fixed`` (the end of a text) keeps class 0 to itself. The start deals
    items by frequency. Gains follow from sums of x log x over the rows and columns that a move changes.
    """
    m = len(pairs)
    weight = pairs.sum(axis=0) + pairs.sum(axis=1)
    order = [i for i in np.argsort(-weight, kind="stable") if i != fixed]
    cls = np.zeros(m, np.int64)
    for rank, i in enumerate(order):
        cls[i] = 1 + rank % (classes - 1)
    onehot = np.zeros((m, classes))
    onehot[np.arange(m), cls] = 1
    after = pairs @ onehot  # item x class that follows
    before = pairs.T @ onehot  # item x class that precedes
    grid = onehot.T @ after

    def f(x):
        return x * np.log(np.maximum(x, 1))

    for _ in range(sweeps):
        moved = 0
        for i in order:
            own = cls[i]
            r, l, s = after[i].copy(), before[i].copy(), pairs[i, i]
            if not r.any() and not l.any():
                continue
            # Take the item out of its class; r and l then no longer count its own repeats.
            r[own] -= s
            l[own] -= s
            grid[own] -= r
            grid[:, own] -= l
            grid[own, own] -= s
            rows, cols = grid.sum(axis=1), grid.sum(axis=0)
            nr, nl = r.sum() + s, l.sum() + s
            gain = (f(grid + r) - f(grid)).sum(axis=1) + (f(grid + l[:, None]) - f(grid)).sum(axis=0)
            d = np.diag(grid)
            gain += f(d + r + l + s) - f(d + r) - f(d + l) + f(d)
            gain -= f(rows + nr) - f(rows) + f(cols + nl) - f(cols)
            gain[0] = -np.inf
            new = int(gain.argmax())
            if gain[new] <= gain[own] + 1e-9:
                new = own
            grid[new] += r
            grid[:, new] += l
            grid[new, new] += s
            if new != own:
                moved += 1
                cls[i] = new
                after[:, own] -= pairs[:, i]
                after[:, new] += pairs[:, i]
                before[:, own] -= pairs[i]
                before[:, new] += pairs[i]
        if not moved:
            break
    return cls


def _f(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1))


def likelihood(grid: np.ndarray) -> float:
    """The part of the training likelihood that depends on the classes."""
    return float(_f(grid).sum() - _f(grid.sum(axis=1)).sum() - _f(grid.sum(axis=0)).sum())


def contexts(words: np.ndarray, cls: np.ndarray, classes: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(word, code, n) of a run of texts, sorted. Codes: class after, ``classes`` + class before, 2 * ``classes`` the word itself."""
    width = 2 * classes + 1
    # The narrowest type that holds every key: sorted in place, it halves time and memory.
    kind = np.uint32 if len(cls) * width < 1 << 32 else np.int64
    a, cls = words.astype(kind), cls.astype(kind)
    b = np.concatenate([np.zeros(1, kind), a])[:-1]  # the end of a text stands before the next one
    same = a == b
    x, y = a[~same], b[~same]
    keys = np.concatenate([y * width + cls[x], x * width + classes + cls[y], a[same] * width + 2 * classes])
    del a, b, x, y, same
    keys.sort()
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    n = np.diff(np.append(first, len(keys)))
    keys = keys[first]
    return keys // width, keys % width, n


def moves(grid: np.ndarray, own: np.ndarray, word: np.ndarray, code: np.ndarray, n: np.ndarray) -> np.ndarray:
    """New class of each word of a parallel sweep, from its sparse (word, code, n) and the grid at the sweep's start.

    The word is taken out of its own class and put where the likelihood gains most; other words stay in the grid
    as they were. Words without counts and class 0 (the end of a text) stay.
    """
    k = len(grid)
    cells = np.vstack([grid.T, grid, np.diag(grid)[None]])  # code x candidate class
    logs = _f(cells)
    order = np.argsort(word, kind="stable")
    word, code, n = word[order], code[order], n[order].astype(float)
    who, start = np.unique(word, return_index=True)
    if not len(who):
        return own.copy()
    mine = own[word]
    few = n <= FEW
    table = np.stack([_f(cells + j) - logs for j in range(FEW + 1)])
    gain = np.empty((len(n), k))
    gain[few] = table[n[few].astype(np.int64), code[few]]
    gain[~few] = _f(cells[code[~few]] + n[~few, None]) - logs[code[~few]]
    at = np.arange(len(word))
    gain[at, mine] = logs[code, mine] - _f(cells[code, mine] - n)
    total = np.add.reduceat(gain, start, axis=0)
    home, at = own[who], np.arange(len(who))
    for side, sums in ((code < k, grid.sum(axis=1)), ((code >= k) & (code < 2 * k), grid.sum(axis=0))):
        m = np.add.reduceat(np.where(side | (code == 2 * k), n, 0.0), start)
        cost = _f(sums + m[:, None]) - _f(sums)
        cost[at, home] = _f(sums[home]) - _f(sums[home] - m)
        total -= cost
    total[:, 0] = -np.inf
    best = total.argmax(axis=1)
    stay = (home == 0) | (total[at, best] <= total[at, home] + 1e-9)
    out = own.copy()
    out[who] = np.where(stay, home, best)
    return out


def _grid(sums: DataFrame, size: int) -> np.ndarray:
    """Sums of (pair, n) rows as a square table."""
    with tidy(sums.sparkSession):
        table = sums.groupBy("pair").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(size * size)
    out[table.column("pair").to_numpy()] = table.column("n").to_numpy()
    return out.reshape(size, size)


def _pair_table(counts: np.ndarray) -> pa.Table:
    at = np.flatnonzero(counts)
    return pa.table([pa.array(at), pa.array(counts.ravel()[at].astype(np.int64))], ["pair", "n"])


def _run_of(texts: pa.Table) -> np.ndarray:
    """The training texts of a block, one after the other."""
    raw = [r.as_py() for r, h in zip(texts.column("numbers"), texts.column("held_out").to_pylist(), strict=True) if not h]
    return np.frombuffer(b"".join(raw), "<u4")


def _by_number(known: pa.Table, column: str, kind: type) -> np.ndarray:
    number = known.column("number").to_numpy()
    out = np.zeros(len(number), kind)
    out[number] = known.column(column).to_numpy()
    return out


LISTS = "block long, number int, word_key long, c long, first boolean, item int, cls int"
KEPT = ["block", "number", "word_key", "c", "first", "item", "cls"]


def sweep(texts: DataFrame, lists: DataFrame, classes: int) -> tuple[DataFrame, float]:
    """One parallel exchange of every training word: the lists with new classes, and the likelihood before it.

    A word's counts of classes around it are sparse, come from every block that holds the word and meet by the
    word's 64-bit hash: one row a block at most.
    """

    def look(left: pa.Table, right: pa.Table) -> pa.Table:
        cls = _by_number(right, "cls", np.int64)
        word, code, n = contexts(_run_of(left), cls, classes)
        packed = np.stack([code, n], axis=1).astype("<u4")
        ends = np.searchsorted(word, np.arange(len(cls) + 1)) * 8
        buffers = [None, pa.py_buffer(ends.astype("<i4").tobytes()), pa.py_buffer(packed.tobytes())]
        around = pa.Array.from_buffers(pa.binary(), len(cls), buffers)
        return right.select(KEPT).sort_by("number").append_column("around", around)

    def entries(batch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        raw = batch.column("around").to_pylist()
        found = np.frombuffer(b"".join(raw), "<u4").reshape(-1, 2).astype(np.int64)
        return np.repeat(np.arange(len(raw)), [len(r) // 8 for r in raw]), found[:, 0], found[:, 1]

    def add(batches):
        counts = np.zeros(classes * classes)
        for batch in batches:
            row, code, n = entries(batch)
            own = batch.column("cls").to_numpy().astype(np.int64)[row]
            after, self_ = code < classes, code == 2 * classes
            counts += np.bincount(own[after] * classes + code[after], n[after], len(counts))
            counts += np.bincount(own[self_] * (classes + 1), n[self_], len(counts))
        yield from _pair_table(counts).to_batches()

    seen = materialise(texts.groupBy("block").cogroup(lists.groupBy("block")).applyInArrow(look, f"{LISTS}, around binary"))
    grid = _grid(seen.select("cls", "around").mapInArrow(add, "pair long, n long"), classes)

    def exchange_all(batches):
        def move(table: pa.Table) -> list[pa.RecordBatch]:
            table = table.combine_chunks()
            _, first, word = np.unique(table.column("word_key").to_numpy(), return_index=True, return_inverse=True)
            row, code, n = entries(table)
            # The same code from several blocks is one count.
            keys, at = np.unique(word[row] * (2 * classes + 1) + code, return_inverse=True)
            n = np.bincount(at, n, len(keys)) if len(keys) else np.zeros(0)
            own = table.column("cls").to_numpy().astype(np.int64)[first]
            new = moves(grid, own, keys // (2 * classes + 1), keys % (2 * classes + 1), n)[word]
            out = table.select(KEPT[:-1]).append_column("cls", pa.array(new.astype(np.int32)))
            return out.to_batches(max_chunksize=20_000)

        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            key = batch.column("word_key").to_numpy()
            # The last word may go on in the next batch.
            cut = int(np.searchsorted(key, key[-1]))
            if cut or held and held[-1].column("word_key")[-1].as_py() != key[-1]:
                yield from move(pa.Table.from_batches([*held, batch.slice(0, cut)]))
                held = []
            held.append(batch.slice(cut))
        if held:
            yield from move(pa.Table.from_batches(held))

    by_word = seen.repartition("word_key").sortWithinPartitions("word_key")
    new = materialise(by_word.mapInArrow(exchange_all, LISTS))
    forget(seen)
    return new, likelihood(grid)


def classed(texts: DataFrame, lists: DataFrame, of_item: np.ndarray, first_ending: int, classes: int, n: int, v: int) -> tuple[DataFrame, np.ndarray, np.ndarray]:
    """Texts as class numbers with their word-level figures, the table of class pairs and the tokens of each class."""
    trained = lists.where(F.col("first") & (F.col("c") > 0))
    total, members = np.zeros(classes), np.zeros(classes)
    for r in trained.groupBy("cls").agg(F.sum("c").alias("n"), F.count("*").alias("v")).collect():
        total[r.cls], members[r.cls] = r.n, r.v
    votes = np.zeros((len(of_item), classes))
    for r in trained.where(F.col("item") >= first_ending).groupBy("item", "cls").count().collect():
        votes[r.item, r.cls] = r["count"]
    unseen = np.where(votes.any(axis=1), votes.argmax(axis=1), of_item)
    base_floor, floor = n + 0.5 * (v + 1), total + 0.5 * (members + 1)

    def look_up(left: pa.Table, right: pa.Table) -> pa.Table:
        c, cls = _by_number(right, "c", np.int64), _by_number(right, "cls", np.int64)
        cls = np.where(c > 0, cls, unseen[_by_number(right, "item", np.int64)])
        base, share = np.log10((c + 0.5) / base_floor), np.log10((c + 0.5) / floor[cls])
        out = []
        for raw in left.column("numbers"):
            ids = np.frombuffer(raw.as_py(), "<u4")
            out.append((len(ids), int((c[ids] > 0).sum()), float(base[ids].sum()), float(share[ids].sum()), cls[ids].astype("<u2").tobytes()))
        columns = list(zip(*out, strict=True)) or [[]] * 5
        return pa.table(
            [
                left.column("doc_id"),
                left.column("held_out"),
                *(pa.array(x, t) for x, t in zip(columns, (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary()), strict=True)),
            ],
            ["doc_id", "held_out", "n_tokens", "n_known", "base_score", "share", "classes"],
        )

    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, share double, classes binary"
    seen = materialise(texts.groupBy("block").cogroup(lists.groupBy("block")).applyInArrow(look_up, schema))

    def add(batches):
        counts = np.zeros(classes * classes)
        for batch in batches:
            for raw in batch.column("classes"):
                k = np.frombuffer(raw.as_py(), "<u2").astype(np.int64)
                counts += np.bincount(np.concatenate([[0], k])[:-1] * classes + k, minlength=len(counts))
        yield from _pair_table(counts).to_batches()

    return seen, _grid(seen.where("not held_out").select("classes").mapInArrow(add, "pair long, n long"), classes), total


def score(docs: DataFrame, heads: int = HEADS, endings: int = ENDINGS, classes: int | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (log10) and perplexity of every text.

    Trains on the rows whose crc32(doc_id) mod 5 is not 1. Every word of the training rows has a class of its own
    choice: a first exchange deals the ``heads`` most frequent words one by one and all others by their ending (last
    two characters, in ``endings`` hash groups); from there parallel sweeps move every word by its own sparse counts
    of classes before and after it. A sweep that does not raise the likelihood is taken back. Only words never seen
    in training go by their ending: to the class that most trained words of that ending group have. A text's
    probability is the product of P(class | class before) and P(word | class), each class with room for one unseen word.
    Ties in frequency go by word. Null text is empty and scores its end alone; repeated rows count again; with no
    training row every known count is 0 and the scores stay finite; an empty table gives an empty result; other
    columns are left behind.

    Counts cover the whole corpus and grow with its vocabulary: words are summed in one shuffle of (block, word)
    rows, at most one row a block for the commonest word; a sweep sends the classes to the blocks and the counts
    back. Only tables of classes and of the start's items come to the driver.
    """
    parts = materialise(blocks(docs, doc_id, text))
    words = parts.where("word is not null").select("block", "word", "number", "n_train")
    by_word = Window.partitionBy("word")
    counted = materialise(
        words.select(
            "block",
            "word",
            "number",
            F.sum("n_train").over(by_word).alias("c"),
            (F.col("block") == F.min("block").over(by_word)).alias("first"),
        )
    )
    each = counted.where("first").select("word", "c")
    n, v = each.select(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.when(F.col("c") > 0, 1))).first()
    classes = classes or class_count(v)
    top = each.where((F.col("c") > 0) & (F.col("word") != F.lit(END))).orderBy(F.desc("c"), "word").limit(heads)
    head_words = [bytes(r.word) for r in top.collect()]
    spark = docs.sparkSession
    head = spark.createDataFrame(
        [(END, 0), *((w, i + 1) for i, w in enumerate(head_words))], "head_word binary, head int"
    )
    first_ending = len(head_words) + 1
    items = first_ending + endings
    ending = F.pmod(F.xxhash64(F.substring(F.col("word").cast("string"), -2, 2)), F.lit(endings)).cast("int") + first_ending

    def named(df: DataFrame) -> DataFrame:
        return df.join(F.broadcast(head), F.col("word") == F.col("head_word"), "left").withColumn(
            "item", F.coalesce("head", ending)
        )

    texts = parts.where("word is null").select("block", "doc_id", "held_out", "numbers")
    lists = materialise(
        named(counted).select("block", "number", F.xxhash64("word").alias("word_key"), "c", "first", "item", F.lit(0).alias("cls"))
    )
    forget(counted)

    def start(left: pa.Table, right: pa.Table) -> pa.Table:
        a = _by_number(right, "item", np.int64)[_run_of(left)]
        return _pair_table(np.bincount(np.concatenate([[0], a])[:-1] * items + a, minlength=items * items))

    # Bounded by the square of the item count, whatever the corpus.
    pairs = _grid(texts.groupBy("block").cogroup(lists.groupBy("block")).applyInArrow(start, "pair long, n long"), items)
    of_item = exchange(pairs, 0, classes)
    lists = lists.withColumn("cls", F.get(F.lit(of_item.astype(np.int32).tolist()), F.col("item")))

    kept, best = lists, -np.inf
    for _ in range(WORD_SWEEPS):
        new, before = sweep(texts, lists, classes)
        if before <= best:
            lists = kept
            break
        kept, best, lists = lists, before, new
    seen, grid, total = classed(texts, lists, of_item, first_ending, classes, n, v)
    if likelihood(grid) < best:
        seen, grid, total = classed(texts, kept, of_item, first_ending, classes, n, v)
    share = (total + 0.5) / (total.sum() + 0.5 * classes)
    follow = np.log10((grid + PRIOR * share) / (grid.sum(axis=1, keepdims=True) + PRIOR))

    def finish(batches):
        for batch in batches:
            out = []
            for raw in batch.column("classes"):
                k = np.frombuffer(raw.as_py(), "<u2").astype(np.int64)
                out.append(float(follow[np.concatenate([[0], k])[:-1], k].sum()))
            score = pa.array(np.array(out) + batch.column("share").to_numpy())
            names = ["doc_id", "held_out", "n_tokens", "n_known", "base_score"]
            yield pa.RecordBatch.from_arrays([*(batch.column(x) for x in names), score], [*names, "score"])

    scored = seen.mapInArrow(finish, "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return scored.select(
        "doc_id",
        "held_out",
        "n_tokens",
        "n_known",
        F.lit(n).cast("long").alias("train_tokens"),
        "base_score",
        "score",
        F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")).alias("perplexity"),
    )
