"""The pipeline's stages on the small tables, each against a brute-force version of it."""

import math
import re
from collections import Counter

import corpus_pipeline as C
import numpy as np
import public_tokenizers as P
from tokenizers import Tokenizer

from slotlens.llm import near_copies, quality, secrets
from slotlens.llm.common import materialise


def plain_score(model, table, names):
    z = np.full(len(table), model.intercept)
    for rule, weight in zip(model.rules, model.weights, strict=True):
        z += weight * rule.holds(table[names].to_numpy(float), names)
    return 1 / (1 + np.exp(-z))


def test_compiled_rules_equal_numpy(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = quality.fit(docs, labels)
    assert model.rules
    table = quality.with_statistics(docs).toPandas()
    names = [c for c in table.columns if c != "doc_id"]
    want = dict(zip(table["doc_id"], plain_score(model, table, names), strict=True))
    got = {r.doc_id: r for r in quality.score(docs, model).collect()}
    assert got.keys() == want.keys() and all(abs(got[i].score - want[i]) < 1e-9 for i in want)
    assert all(r.predicted == (r.score >= 0.3) for r in got.values())
    text = {r.doc_id: r.text or "" for r in docs.collect()}
    for row in table.itertuples():
        t = text[row.doc_id]
        assert row.chars == len(t) and row.words == len(t.split(" ")) and row.lines_per_word == len(t.split("\n")) / len(t.split(" "))
        assert abs(row.distinct_words - len(set(t.split(" "))) / len(t.split(" "))) < 1e-12
        assert abs(row.exclamations - t.count("!") / len(t.split(" "))) < 1e-12
    truth = {r.doc_id: r.quality for r in labels.collect()}
    held = [(r.score, truth[i]) for i, r in got.items() if r.held_out and truth.get(i) is not None]
    good, bad = [s for s, y in held if y], [s for s, y in held if not y]
    assert np.mean([a > b for a in good for b in bad]) > 0.9


def shingles(text):
    w = text.split()
    k = min(5, len(w))
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if k else frozenset()


def groups_of(rows):
    root = {i: i for i, _ in rows}

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    sets = [(i, shingles(t)) for i, t in rows]
    for k, (i, a) in enumerate(sets):
        for j, b in sets[:k]:
            if a == b or a and b and len(a & b) / len(a | b) >= 0.8:
                x, y = sorted((find(i), find(j)))
                root[y] = x
    return {i for i, _ in rows if find(i) == i}


def masked(rows):
    """Plain Python masking of (id, text, source) rows."""

    def found(text):
        for kind, (pattern, group, least) in secrets.KINDS.items():
            for m in re.finditer(pattern, text):
                if len(m[group]) >= least and (kind != "upper" or re.search("[A-F]", m[group])):
                    yield kind, m, m[group]

    owners = {}
    for i, t, s in rows:
        for _, _, v in found(t):
            owners.setdefault(v, {}).setdefault(s, set()).add(i)

    def live(v):
        repos = [len(x) for x in owners[v].values()]
        n = Counter(v)
        bits = -sum(c / len(v) * math.log2(c / len(v)) for c in n.values())
        copied = len(repos) >= secrets.COPIED_AT and 2 * max(repos) <= sum(repos)
        return not copied and bits >= secrets.LIVE_BITS and not re.search(secrets.PLACEHOLDER, v)

    out = {}
    for i, t, _ in rows:
        bad = {v for _, _, v in found(t) if live(v)}
        for kind in sorted(secrets.KINDS, key=lambda k: k != "pem"):
            pattern, group, _ = secrets.KINDS[kind]
            t = re.sub(pattern, lambda m, g=group: m[0][: len(m[0]) - len(m[g])] + secrets.MASK if m[g] in bad else m[0], t)
        out[i] = t
    return out


def test_stages_equal_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels, names = spark.read.parquet(f"{sf}/labels.parquet"), docs.columns
    stages = [stage for _, stage in C.STAGES]

    good = materialise(stages[0](spark, docs, sf))
    model = quality.fit(docs, labels)
    table = quality.with_statistics(docs).toPandas()
    score = plain_score(model, table, [c for c in table.columns if c != "doc_id"])
    assert {r.doc_id for r in good.collect()} == set(table["doc_id"][score >= 0.3])

    single = materialise(stages[1](spark, good, sf))
    assert {r.doc_id for r in single.collect()} == groups_of([(r.doc_id, r.text or "") for r in good.collect()])

    extra = [(10_000 + i, f'{w} password = "h3Gv9sWq2LpN{i}" and AKIAQCN5VJTUYMSSXKC{i}', "en", f"x{i}", 0) for i, w in enumerate("abc")]
    extra += [(20_000 + i, f'note {i}: token = "q8Zr4kT1mX7c"', "en", f"x{i}", 0) for i in range(4)]
    more = single.unionByName(spark.createDataFrame(extra, single.schema))
    safe = materialise(stages[2](spark, more, sf))
    want = masked([(r.doc_id, r.text or "", r.source or "") for r in more.collect()])
    rows = safe.collect()
    assert {r.doc_id: r.text or "" for r in rows} == want and safe.columns == names
    assert sum(secrets.MASK in t for t in want.values()) >= 3 and want[20_000] == extra[3][1]
    assert all(r.n_chars == len(r.text) for r in rows if secrets.MASK in (r.text or ""))

    lib = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    packed = stages[3](spark, safe, sf).collect()
    length = Counter()
    for r in packed:
        length[r.doc_id] += r.length
    assert length == Counter({i: len(lib.encode(t, add_special_tokens=False).ids) + 1 for i, t in want.items()})
    fill = Counter()
    for r in sorted(packed, key=lambda r: (r.sequence_id, r.offset)):
        assert fill[r.sequence_id] == r.offset and r.offset + r.length <= 1024
        fill[r.sequence_id] += r.length


def test_stages_take_odd_and_empty_tables(spark, sf, odd_docs):
    odd = odd_docs.withColumnRenamed("size", "live")
    for k, (_, stage) in enumerate(C.STAGES):
        out = stage(spark, odd, sf)
        assert out.count() > 0 and stage(spark, odd.limit(0), sf).count() == 0
        if k + 1 < len(C.STAGES):
            assert out.columns == odd.columns
    assert near_copies.join(odd.limit(0)).count() == 0


def test_queries_are_registered():
    import __spark_entry__ as entry

    found = {q.split("_")[0] for q in entry.queries() if q.startswith("op")}
    assert found == {f"op{i}" for i in range(1, 11)} and "pipeline" in entry.queries()
