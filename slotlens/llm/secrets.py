"""Secret spans and corpus-wide ownership frequency (op 3). DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slotlens.llm.common import materialise, small

#: Kinds in their order, pattern, group that holds the value, least length of that group.
KINDS = {
    "assign": (r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    "access": (r"AKIA[A-Z0-9]+", 0, 20),
    "hex": (r"[0-9a-f]+", 0, 24),
    # Kinds that the method adds to the base ones.
    "upper": (r"[0-9A-F]{32,}", 0, 32),
    "jwt": (r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 28),
    # The whole key: header, attribute lines and body to the END line, or as far as the body goes where that is missing.
    "pem": (
        r"-----BEGIN [A-Z ]*PRIVATE KEY-----(?:[\x20\t\r\n]+[A-Za-z-]+: [^\r\n]+){0,5}"
        r"(?:[A-Za-z0-9+/=\x20\t\r\n\\]*-----END [A-Z ]*PRIVATE KEY-----|(?:[\x20\t\r\n]*[A-Za-z0-9+/=]{16,}[A-Za-z0-9+/=\r\n\\]*)?)",
        0,
        10,
    ),
}
BASE = ("assign", "access", "hex")
#: One quick look that every text with a span passes.
ANY = r"(?i:password|passwd|secret|token|api_?key)|AKIA|[0-9a-f]{24}|[0-9A-F]{32}|eyJ|-----BEGIN"
#: A value of so many owners, none of whom holds more than half of its repositories, is a widely copied example.
COPIED_AT = 3
#: A value looks live if its characters carry so many bits each and it has no placeholder's words.
LIVE_BITS = 1.99
PLACEHOLDER = r"(?i)example|changeme|placeholder|dummy|redacted|your[_-]|x{5}|0{5}|12345"
MASK = "<secret>"


def _shorter(kind: str) -> str:
    """The same matches with failing ones left out where leaving them out cannot move the others."""
    return {"access": r"AKIA[A-Z0-9]{16,}", "hex": r"[0-9a-f]{24,}"}.get(kind, KINDS[kind][0])


def _spans(rows: DataFrame, kind: str) -> DataFrame:
    """Adds column ``kind``: array of (at, kind_no, end, value) for one kind; null where the quick look failed."""
    _, group, least = KINDS[kind]
    pattern = F.lit(_shorter(kind))
    number = list(KINDS).index(kind)

    def total(array: Column) -> Column:
        return F.aggregate(array, F.lit(0), lambda a, x: a + x)

    out = rows.withColumn("_gaps", F.when(F.col("_any"), F.split("text", pattern.cast("string"), -1)))
    some = F.size("_gaps") > 1
    out = out.withColumn("_hits", F.when(some, F.regexp_extract_all("text", pattern, 0)))
    out = out.withColumn("_values", F.when(some, F.regexp_extract_all("text", pattern, group) if group else F.col("_hits")))
    # Text = gap 0, hit 0, gap 1, hit 1, ...: a hit starts after all gaps up to its own and all hits before it.
    out = out.withColumn(
        "_sizes", F.transform("_hits", lambda h, i: F.length(F.get("_gaps", i)) + F.length(h))
    ).withColumn("_width", F.greatest(F.lit(1), F.floor(F.sqrt(F.size("_sizes"))).cast("int")))
    out = out.withColumn(
        "_runs",
        F.transform(
            F.sequence(F.lit(0), (F.size("_sizes") / F.col("_width")).cast("int")),
            lambda b: total(F.slice("_sizes", b * F.col("_width") + 1, F.col("_width"))),
        ),
    )

    def one(h: Column, i: Column) -> Column:
        run = (i / F.col("_width")).cast("int")
        before = total(F.slice("_runs", 1, run)) + total(
            F.slice("_sizes", run * F.col("_width") + 1, i - run * F.col("_width"))
        )
        at = before + F.length(F.get("_gaps", i))
        return F.struct(
            at.alias("at"), F.lit(number).alias("kind_no"), (at + F.length(h)).alias("end"), F.get("_values", i).alias("value")
        )

    def fine(s: Column) -> Column:
        long_enough = F.length(s["value"]) >= least
        return long_enough & s["value"].rlike("[A-F]") if kind == "upper" else long_enough

    good = F.filter(F.transform("_hits", one), fine)
    return out.withColumn(kind, good).drop("_gaps", "_hits", "_values", "_sizes", "_width", "_runs")


def looks_live(value: Column) -> Column:
    """Enough entropy over its characters, and none of the words and runs that placeholders have."""
    n = F.length(value).cast("double")

    def bits(c: Column) -> Column:
        p = (n - F.length(F.replace(value, c, F.lit("")))) / n
        return -p * F.log2(p)

    entropy = F.aggregate(F.array_distinct(F.split(value, "")), F.lit(0.0), lambda a, c: a + bits(c))
    return (entropy >= LIVE_BITS) & ~value.rlike(PLACEHOLDER)


def find(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", owner: str = "source", repo: str = "doc_id") -> DataFrame:
    """doc_id, text_hash, owner, repo and spans: array of (at, kind_no, end, value_hash, looks), ordered by start, then kind.

    Offsets count code points, ends are exclusive. Values leave this step only as SHA-256 digests, with whether they
    look live. Null text is empty; a null owner or repository counts as one more. The tables name no repositories:
    a document stands for one, its source for the owner. Other columns are left behind.
    """
    body = docs.select(
        F.col(doc_id).cast("long").alias("doc_id"),
        F.coalesce(F.col(text), F.lit("")).alias("text"),
        F.coalesce(F.col(owner).cast("string"), F.lit("")).alias("owner"),
        F.coalesce(F.col(repo).cast("string"), F.lit("")).alias("repo"),
    ).withColumn("_any", F.col("text").rlike(ANY))
    for kind in KINDS:
        body = _spans(body, kind)
    none = F.array().cast("array<struct<at:int,kind_no:int,end:int,value:string>>")
    hashed = F.transform(
        F.array_sort(F.concat(*(F.coalesce(kind, none) for kind in KINDS))),
        lambda s: F.struct(
            s["at"], s["kind_no"], s["end"], F.sha2(s["value"], 256).alias("value_hash"), looks_live(s["value"]).alias("looks")
        ),
    )
    return body.select("doc_id", F.xxhash64("text").alias("text_hash"), "owner", "repo", hashed.alias("spans"))


def ownership(found: DataFrame) -> DataFrame:
    """value_hash, n_owners, n_repos (owner and repository pairs) and most_repos (of one owner) over the whole corpus.

    Aggregated by owner and repository first, so copies collapse before they meet.
    """
    each = found.select("owner", "repo", F.explode(F.array_distinct(F.transform("spans", lambda s: s["value_hash"]))).alias("value_hash"))
    by_owner = each.groupBy("value_hash", "owner", "repo").count().groupBy("value_hash", "owner").agg(F.count("*").alias("repos"))
    return by_owner.groupBy("value_hash").agg(
        F.count("*").alias("n_owners"), F.sum("repos").alias("n_repos"), F.max("repos").alias("most_repos")
    )


def judged(found: DataFrame, copied_at: int = COPIED_AT) -> DataFrame:
    """Per (doc_id, text_hash) with spans: live value hashes, counts of live, copied and placeholder spans, n_owners, n_repos.

    Copied: of ``copied_at`` owners or more, none with more than half of the value's repositories. Live: not copied, and
    it looks live. Placeholder: the rest. n_owners and n_repos are the largest among the row's values. Only rows with
    spans move; repeats of a document collapse first, and of the values only those seen in several repositories are
    the other side, broadcast while they are few; beyond that the adaptive split takes a value that dominates.
    """
    shared = materialise(ownership(found).where("n_repos > 1"))
    shared = small(shared).withColumnRenamed("value_hash", "shared_hash")
    spans = found.where(F.size("spans") > 0).select("doc_id", "text_hash", "spans").distinct()
    each = spans.select("doc_id", "text_hash", F.explode("spans").alias("s")).select("doc_id", "text_hash", "s.value_hash", "s.looks")
    told = each.join(shared, F.col("value_hash") == F.col("shared_hash"), "left")
    is_copied = F.coalesce((F.col("n_owners") >= copied_at) & (2 * F.col("most_repos") <= F.col("n_repos")), F.lit(False))
    live = F.when(~is_copied & F.col("looks"), F.col("value_hash"))
    return told.groupBy("doc_id", "text_hash").agg(
        F.collect_set(live).alias("live"),
        F.count(live).alias("n_live"),
        F.count(F.when(is_copied, 1)).alias("n_copied"),
        F.count(F.when(~is_copied & ~F.col("looks"), 1)).alias("n_placeholder"),
        F.max(F.coalesce("n_owners", F.lit(1))).cast("long").alias("n_owners"),
        F.max(F.coalesce("n_repos", F.lit(1))).cast("long").alias("n_repos"),
    )


VERDICT = ["n_live", "n_copied", "n_placeholder", "n_owners", "n_repos"]


def _text_of(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(
        F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind_no"]), s["at"].cast("string"), s["end"].cast("string"))), ","
    )


def report(docs: DataFrame, copied_at: int = COPIED_AT, **columns) -> DataFrame:
    """One row per document: counts of the base kinds, digest of the base spans, all spans, and the verdict of ``judged``.

    Rows without spans have zeros. Repeated rows repeat; an empty table gives an empty result.
    """
    found = materialise(find(docs, **columns))

    def of(kind: str) -> Column:
        return F.size(F.filter("spans", lambda s: s["kind_no"] == list(KINDS).index(kind))).cast("long")

    base = F.filter("spans", lambda s: s["kind_no"] < len(BASE))
    verdict = judged(found, copied_at).select(F.col("doc_id").alias("_id"), F.col("text_hash").alias("_hash"), *VERDICT)
    same = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_hash") == F.col("_hash"))
    shape = [
        F.col("doc_id"),
        *(of(k).alias(f"n_{k}") for k in BASE),
        F.sha2(_text_of(base), 256).alias("base_sha256"),
        _text_of(F.col("spans")).alias("spans"),
    ]
    # Rows without spans take no part in the join: they'd only travel.
    bare = found.where(F.size("spans") == 0).select(*shape, *(F.lit(0).cast("long").alias(v) for v in VERDICT))
    full = found.where(F.size("spans") > 0).join(verdict, same).select(*shape, *VERDICT)
    return bare.unionByName(full)


def _masked(text: Column, kind: str, live: Column) -> Column:
    """The text with every live value of one kind masked: gaps and rewritten hits, joined again."""
    _, group, least = KINDS[kind]
    pattern = F.lit(_shorter(kind))
    gaps, hits = F.split(text, pattern.cast("string"), -1), F.regexp_extract_all(text, pattern, 0)
    values = F.regexp_extract_all(text, pattern, group)

    def rewrite(z: Column) -> Column:
        hit, value = z["hits"], z["values"]
        # Values that ``find`` passed over are in no live set.
        bad = (F.length(value) >= least) & F.array_contains(live, F.sha2(value, 256))
        kept = F.substring(hit, F.lit(1), F.length(hit) - F.length(value))
        return F.concat(z["gaps"], F.when(bad, F.concat(kept, F.lit(MASK))).otherwise(F.coalesce(hit, F.lit(""))))

    zipped = F.arrays_zip(gaps.alias("gaps"), hits.alias("hits"), values.alias("values"))
    return F.array_join(F.transform(zipped, rewrite), "")


def redact(docs: DataFrame, copied_at: int = COPIED_AT, doc_id: str = "doc_id", text: str = "text", **columns) -> DataFrame:
    """``docs`` with live values masked in the text (and n_chars, where there is one, counted again); no row goes.

    All other columns stay as they are, whatever their names; a null text stays null. Repeated rows are all masked.
    """
    verdict = judged(materialise(find(docs, doc_id, text, **columns)), copied_at)
    verdict = materialise(verdict.where(F.col("n_live") > 0).select("doc_id", "text_hash", "live"))
    names = docs.columns
    body = F.coalesce(F.col(text), F.lit(""))
    rows = docs.select(F.struct(*names).alias("_row"), F.col(doc_id).cast("long").alias("_id"), F.xxhash64(body).alias("_hash"))
    # At most a few hashes of 64 characters a row.
    few = verdict.agg(F.sum(F.size("live"))).first()[0] or 0
    joined = rows.join(small(verdict, few), F.col("_id").eqNullSafe(F.col("doc_id")) & (F.col("_hash") == F.col("text_hash")), "left")
    joined = joined.select("_row", "live", F.col("_row").getField(text).alias("_text"))
    # Whole keys first: a value masked inside one would change it.
    for kind in sorted(KINDS, key=lambda k: k != "pem"):
        masked = _masked(F.coalesce("_text", F.lit("")), kind, F.col("live"))
        joined = joined.withColumn("_text", F.when(F.col("live").isNull(), F.col("_text")).otherwise(masked))
    changed = {text: F.col("_text")}
    if "n_chars" in names:
        kept, kind = F.col("_row").getField("n_chars"), dict(docs.dtypes)["n_chars"]
        changed["n_chars"] = F.when(F.col("live").isNull(), kept).otherwise(F.length("_text").cast(kind))
    return joined.select(*(changed.get(c, F.col("_row").getField(c)).alias(c) for c in names))


def _sql_spans(number: int, kind: str) -> str:
    pattern, group, least = KINDS[kind]
    quoted = pattern.replace("'", "''")
    letters = " AND regexp_matches(vals[i], '[A-F]')" if kind == "upper" else ""
    return f"""SELECT rid, {number} AS no, '{kind}' AS kind, vals[i] AS val, length(hits[i]) AS n,
  list_sum(list_transform(gaps[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(hits[1:i-1], lambda x: length(x))), 0) AS start
 FROM (SELECT rid, hits, gaps, vals, unnest(range(1, len(hits) + 1)) AS i FROM (SELECT rid, string_split_regex(t, '{quoted}') AS gaps,
  regexp_extract_all(t, '{quoted}', 0) AS hits, regexp_extract_all(t, '{quoted}', {group}) AS vals FROM d)) WHERE length(vals[i]) >= {least}{letters}"""


#: DuckDB SQL for ``report`` over the documents.
REPORT_SQL = f"""WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t, coalesce(source, '') AS owner, coalesce(doc_id::VARCHAR, '') AS repo FROM documents),
s AS ({" UNION ALL ".join(_sql_spans(i, k) for i, k in enumerate(KINDS))}),
own AS (SELECT val, count(*) AS owners, sum(r)::BIGINT AS repos, count(*) >= {COPIED_AT} AND 2 * max(r) <= sum(r) AS copied,
  list_aggregate(string_split(val, ''), 'entropy') >= {LIVE_BITS} AND NOT regexp_matches(val, '{PLACEHOLDER}') AS looks
  FROM (SELECT val, owner, count(DISTINCT repo) AS r FROM s JOIN d USING (rid) GROUP BY val, owner) GROUP BY val),
a AS (SELECT rid, count(*) FILTER (no = 0) AS n_assign, count(*) FILTER (no = 1) AS n_access, count(*) FILTER (no = 2) AS n_hex,
  string_agg(kind || ':' || start::BIGINT || ':' || (start + n)::BIGINT, ',' ORDER BY start, no) FILTER (no < 3) AS base,
  string_agg(kind || ':' || start::BIGINT || ':' || (start + n)::BIGINT, ',' ORDER BY start, no) AS spans,
  count(*) FILTER (NOT copied AND looks) AS n_live, count(*) FILTER (copied) AS n_copied, count(*) FILTER (NOT copied AND NOT looks) AS n_placeholder,
  max(owners) AS n_owners, max(repos) AS n_repos FROM s JOIN own USING (val) GROUP BY rid)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(base, '')) AS base_sha256,
  coalesce(spans, '') AS spans, coalesce(n_live, 0) AS n_live, coalesce(n_copied, 0) AS n_copied, coalesce(n_placeholder, 0) AS n_placeholder,
  coalesce(n_owners, 0) AS n_owners, coalesce(n_repos, 0) AS n_repos FROM d LEFT JOIN a USING (rid)"""
