"""Range shards from size-weighted key samples (op 7). DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slotlens.llm.common import count_below, literal_table, materialise

SHARDS = 8
#: Fine ranges at least; beyond that one per so many rows, so that no window task grows with the input.
RANGES, ROWS_PER_RANGE = 512, 500_000


def sized(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size (UTF-8 bytes + 1), text_crc32, key (hash of the text): what sharding needs of a row."""
    body = F.coalesce(F.col(text), F.lit(""))
    return docs.select(
        F.col(doc_id).cast("long").alias("doc_id"),
        (F.octet_length(body) + 1).cast("long").alias("size"),
        F.crc32(body).alias("text_crc32"),
        F.xxhash64(body).alias("key"),
    )


def by_bytes(docs: DataFrame, shards: int = SHARDS, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard under the law ``bytes``: sizes near equal.

    Keys are drawn with chance in proportion to size; quantiles of the draw bound fine ranges of the key, whose
    exact sizes are then summed. A key as large as a fine range (many equal texts) is overfull: it leaves its
    range and stays whole in one shard if one has room, else it is subdivided by hash. All other rows go to
    shards in key order, cut where the running size meets what each shard still lacks, never inside a group of
    equal texts. Slots number a shard's rows from 0 without gaps. Null text has size 1; null and repeated ids are
    rows like others; an empty table gives an empty result. Driver-side lists hold one entry a fine range.
    """
    spark = docs.sparkSession
    rows = materialise(sized(docs, doc_id, text))
    n, total = rows.select(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    ranges = max(RANGES, -(-n // ROWS_PER_RANGE))
    draws = 64 * ranges

    # Chance of a row in proportion to its size, by a fixed hash: a re-run task draws the same rows.
    share = (F.pmod(F.xxhash64(F.lit(11), "doc_id", "key"), F.lit(1 << 40)) / float(1 << 40)).cast("double")
    sample = rows.where(share * max(1, total) < F.col("size") * draws)
    cuts = sample.select(F.percentile_approx("key", [i / ranges for i in range(1, ranges)], 100_000)).first()[0]
    heavy_keys = [
        r.key for r in sample.groupBy("key").count().where(F.col("count") >= draws // ranges // 2).select("key").collect()
    ]
    heavy = literal_table(spark, {"heavy_key": ("long", heavy_keys)})
    per_range = max(1, total // ranges)

    marked = rows.join(F.broadcast(heavy), F.col("key") == F.col("heavy_key"), "left")
    weights = {
        r.key: r.size
        for r in marked.where("heavy_key is not null").groupBy("key").agg(F.sum("size").alias("size")).collect()
    }
    # Overfull: several ranges' worth of sub-ranges by hash of the row, about a range each.
    parts = {k: max(1, -(-w // per_range)) for k, w in weights.items()}
    order = {k: i for i, k in enumerate(sorted(parts))}
    split = literal_table(
        spark,
        {
            "heavy_key": ("long", sorted(parts)),
            "heavy_no": ("long", [order[k] for k in sorted(parts)]),
            "parts": ("long", [parts[k] for k in sorted(parts)]),
        },
    )
    dealt = rows.join(F.broadcast(split), F.col("key") == F.col("heavy_key"), "left").select(
        "doc_id",
        "size",
        "text_crc32",
        "key",
        "heavy_no",
        F.pmod(F.xxhash64("doc_id", F.monotonically_increasing_id()), F.coalesce("parts", F.lit(1))).alias("part"),
        count_below(F.col("key"), sorted(set(cuts or []))).alias("range"),
    )
    dealt = materialise(dealt)
    light_sizes = {
        r.range: r.size
        for r in dealt.where("heavy_no is null").groupBy("range").agg(F.sum("size").alias("size")).collect()
    }
    part_sizes: dict[int, dict[int, int]] = {}
    for r in dealt.where("heavy_no is not null").groupBy("heavy_no", "part").agg(F.sum("size").alias("size")).collect():
        part_sizes.setdefault(r.heavy_no, {})[r.part] = r.size

    lacks, homes = [total / shards] * shards, []
    for number, sizes in sorted(part_sizes.items(), key=lambda x: (-sum(x[1].values()), x[0])):
        whole = sum(sizes.values())
        most = max(range(shards), key=lambda s: lacks[s])
        if lacks[most] >= whole:
            homes += [(number, part, most) for part in sizes]
            lacks[most] -= whole
            continue
        for part, size in sorted(sizes.items(), key=lambda x: (-x[1], x[0])):
            to = max(range(shards), key=lambda s: lacks[s])
            homes.append((number, part, to))
            lacks[to] -= size
    room = [max(0.0, x) for x in lacks]
    light_total = sum(light_sizes.values())
    scale = light_total / sum(room) if sum(room) else 0.0
    bounds, at = [], 0.0
    for s in range(shards - 1):
        at += room[s] * scale
        bounds.append(at)
    before, running = {}, 0
    for r in sorted(light_sizes):
        before[r] = running
        running += light_sizes[r]

    starts = literal_table(spark, {"range": ("int", list(before)), "before": ("long", list(before.values()))})
    inside = Window.partitionBy("range").orderBy("key")
    group = Window.partitionBy("range", "key")
    middle = F.col("before") + F.sum("size").over(inside) - F.sum("size").over(group) / 2
    light = (
        dealt.where("heavy_no is null")
        .join(F.broadcast(starts), "range")
        .withColumn("middle", middle)
        .select(
            "doc_id", "size", "text_crc32", "key", F.col("range").cast("long").alias("cell"), F.lit(-1).cast("long").alias("part"),
            F.size(F.filter(F.array(*map(F.lit, bounds)), lambda b: b <= F.col("middle"))).alias("shard"),
        )
    )
    where = literal_table(
        spark,
        {
            "heavy_no": ("long", [h[0] for h in homes]),
            "part": ("long", [h[1] for h in homes]),
            "shard": ("int", [h[2] for h in homes]),
        },
    )
    dense = (
        dealt.where("heavy_no is not null")
        .join(F.broadcast(where), ["heavy_no", "part"])
        .select("doc_id", "size", "text_crc32", "key", (-1 - F.col("heavy_no")).alias("cell"), "part", "shard")
    )
    placed = materialise(light.unionByName(dense))
    counts = placed.groupBy("shard", "cell", "part").count().collect()
    base, seen = [], [0] * shards
    for r in sorted(counts, key=lambda r: (r.shard, r.cell, r.part)):
        base.append((r.shard, r.cell, r.part, seen[r.shard]))
        seen[r.shard] += r["count"]
    offsets = literal_table(
        spark,
        {
            "shard": ("int", [b[0] for b in base]),
            "cell": ("long", [b[1] for b in base]),
            "part": ("long", [b[2] for b in base]),
            "base": ("long", [b[3] for b in base]),
        },
    )
    turn = Window.partitionBy("shard", "cell", "part").orderBy("key", "doc_id", "text_crc32", "size")
    return placed.join(F.broadcast(offsets), ["shard", "cell", "part"]).select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("bytes").alias("law"),
        "shard",
        (F.col("base") + F.row_number().over(turn) - 1).alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )
