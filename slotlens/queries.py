"""Registry of the series engine: one query for each method, variant, baseline, measure and workload."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F

from slotlens.functions import sql as surface
from slotlens.operators import cleanse, cliquecover, fences, landscape, portraits, series, similarity, smoother, spectrum, threshold
from slotlens.oracles import ORACLES  # noqa: F401  (part of the registry)
from slotlens.plans import metrics, pipelines
from slotlens.sources import fixtures as X
from slotlens.sources.tables import read_table

DF_SMALL = (148, 188, 228, 258, 288, 318)


def r6(df: DataFrame, *names: str) -> DataFrame:
    """Derived doubles rounded to six digits, as their oracles are."""
    return df.withColumns({n: F.round(n, 6) for n in names})


def _slots(df: DataFrame, r: int = 24) -> DataFrame:
    return portraits.by_tick(df, r)


def banded(df: DataFrame) -> DataFrame:
    """Fixed map from slot to group by bands of the profile, which stands in for a learned one in SQL."""
    p = F.get(F.array(*map(F.lit, X.PROFILE)), F.col("slot"))
    return df.withColumn("vp_id", F.when(p < 100, 0).when(p < 140, 1).when(p < 170, 2).otherwise(3))


def by_month(df: DataFrame) -> DataFrame:
    return df.withColumn("vld_id", F.month("ts"))


SMALL, LARGE = ["series_id", "vp_id"], ["series_id", "vld_id", "vp_id"]


def _small(spark, sf_dir, model: str) -> DataFrame:
    grouped = banded(_slots(X.month(spark, sf_dir)))
    return cleanse.detect(grouped, fences.build(model, grouped, SMALL), SMALL, fence_rows=4)


def _large(spark, sf_dir, model: str) -> DataFrame:
    grouped = banded(_slots(by_month(X.year(spark, sf_dir))))
    return cleanse.detect(grouped, fences.build(model, grouped, LARGE), LARGE, fence_rows=48)


def _flags(df: DataFrame) -> DataFrame:
    return df.select("tick", F.col("slot").cast("int").alias("slot"), F.col("vp_id").cast("int").alias("vp_id"), F.round("y", 6).alias("y"), "is_polluted", "is_outlier")


def _score(df: DataFrame, name: str) -> DataFrame:
    s = metrics.scores(df).withColumn("strategy", F.lit(name))
    return r6(s.select("strategy", "tp", "fp", "tn", "fn", "accuracy", "precision", "recall", "f_measure"), "accuracy", "precision", "recall", "f_measure")


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


# --- sources, regular series, fixtures ---------------------------------------------------------------------------


def w_month_series(spark, sf_dir):
    return r6(X.month(spark, sf_dir).select("tick", "y_true", "y", "is_polluted", "style"), "y_true", "y")


def w_year_series(spark, sf_dir):
    return r6(X.year(spark, sf_dir).select("tick", "y_true", "y", "is_polluted", "style"), "y_true", "y")


def w_year_mild_series(spark, sf_dir):
    return r6(X.year(spark, sf_dir, X.MILD).select("tick", "y_true", "y", "is_polluted", "style"), "y_true", "y")


def w_weekly_series(spark, sf_dir):
    return X.weekly(spark, sf_dir).select("tick", F.round("y", 10).alias("y"))


def w_house_series(spark, sf_dir):
    one = X.fleet(spark, sf_dir)
    first = one.agg(F.min("series_id").alias("series_id"))
    return r6(one.join(first, "series_id").where(F.col("tick").between(24, 24 * 23 - 1)).select("tick", "y"), "y")


def polluted_series(spark, sf_dir):
    return r6(X.month(spark, sf_dir).where("is_polluted").select("tick", "style", "y_true", "y"), "y_true", "y")


def resample_hourly(spark, sf_dir):
    return r6(X.hourly(spark, sf_dir).select("tick", "y"), "y")


def resample_variants(spark, sf_dir):
    events = read_table(spark, sf_dir, "events")
    kinds = [
        series.regularise(events, "ts", "value", "2024-01-01", 3600, how, ["event_type"]).withColumn("how", F.lit(how))
        for how in ("sum", "mean", "last", "count")
    ]
    return r6(_union(kinds), "y")


def gap_fill(spark, sf_dir):
    full = series.fill_gaps(X.hourly(spark, sf_dir), 0, 719, default=0.0)
    return r6(full.select("tick", "was_missing", "y_filled"), "y_filled")


def missing_ticks(spark, sf_dir):
    events = read_table(spark, sf_dir, "events").withColumn("series_id", F.col("event_type"))
    per = series.regularise(events, "ts", "value", "2024-01-01", 3600, keys=["series_id"])
    return series.missing_ticks(per, 0, 719).select("series_id", "tick")


def validate_events(spark, sf_dir):
    return series.problems(X.hourly(spark, sf_dir))


def gap_default_compare(spark, sf_dir):
    """Zero against a very large default for missing ticks: flags of the boxplot on each."""
    raw = X.hourly(spark, sf_dir)
    out = []
    for name, sentinel in (("zero", False), ("sentinel", True)):
        full = _slots(series.fill_gaps(raw, 0, 719, default=0.0, sentinel=sentinel))
        flagged = cleanse.detect(full, fences.boxplot(full, ["series_id", "slot"], "y_filled"), ["series_id", "slot"], "y_filled", 24)
        out.append(
            flagged.agg(F.count_if("was_missing").alias("missing"), F.count_if(F.col("was_missing") & F.col("is_outlier")).alias("flagged")).withColumn("gap_default", F.lit(name))
        )
    return _union(out)


# --- slots, vectors, spectra -------------------------------------------------------------------------------------


def slot_assignment(spark, sf_dir):
    return _slots(X.month(spark, sf_dir)).select("tick", "slot", "period_ix")


def interval_slots(spark, sf_dir):
    cut = portraits.by_interval(read_table(spark, sf_dir, "events"), "ts", "2024-01-01", 86400.0, 7)
    return cut.groupBy("slot").agg(F.count("*").alias("n"), (F.sum(F.round(F.col("value") * 100).cast("bigint")) / 100.0).alias("total"))


def slot_range_filter(spark, sf_dir):
    return r6(_slots(X.month(spark, sf_dir)).where(F.col("slot").between(0, 9)).select("tick", "slot", "y"), "y")


def portrait_vectors(spark, sf_dir):
    return r6(portraits.vectors(_slots(X.month(spark, sf_dir)), ["series_id", "slot"]), "theta", "mad")


def portrait_vectors_one_pass(spark, sf_dir):
    return r6(portraits.vectors(_slots(X.month(spark, sf_dir)), ["series_id", "slot"], method="one_pass"), "theta", "mad")


def portrait_vectors_approx(spark, sf_dir):
    return portraits.vectors(_slots(X.month(spark, sf_dir)), ["series_id", "slot"], method="approx")


def portrait_vectors_mean_sd(spark, sf_dir):
    return r6(portraits.vectors(_slots(X.month(spark, sf_dir)), ["series_id", "slot"], method="mean_sd"), "theta", "mad")


def landscape_vector(spark, sf_dir):
    s = _slots(X.month(spark, sf_dir))
    out = [portraits.vectors(s, ["series_id"]).withColumn("scope", F.lit("all")), portraits.vectors(s.where("slot < 10"), ["series_id"]).withColumn("scope", F.lit("hours 1-10"))]
    return r6(_union(out), "theta", "mad")


def portrait_spans(spark, sf_dir):
    """Spans of the month's slots merged by bands of their own median."""
    v = r6(portraits.vectors(_slots(X.month(spark, sf_dir)), ["series_id", "slot"]), "theta")
    p = F.col("theta")
    groups = v.withColumn("vp_id", F.when(p < 1.0, 0).when(p < 1.4, 1).when(p < 1.7, 2).otherwise(3))
    return portraits.spans(groups, 1.0).select("vp_id", "span", F.size("intervals").cast("bigint").alias("n_intervals"))


def matrix_view(spark, sf_dir):
    wide = portraits.matrix_view(_slots(X.month(spark, sf_dir)), 24)
    return wide.select("period_ix", *(F.round(str(i), 6).alias(f"h{i}") for i in range(24)))


def matrix_melt(spark, sf_dir):
    wide = portraits.matrix_view(_slots(X.month(spark, sf_dir)), 24)
    return r6(wide.unpivot(["period_ix"], [str(i) for i in range(24)], "slot", "y").select("period_ix", F.col("slot").cast("int").alias("slot"), "y"), "y")


def _bins(df: DataFrame) -> DataFrame:
    # Adding zero makes a negative zero plain.
    return df.select("k", (F.round("re", 4) + 0.0).alias("re"), (F.round("im", 4) + 0.0).alias("im"))


def power_spectrum(spark, sf_dir):
    return _bins(spectrum.dft_bins(X.month(spark, sf_dir), list(range(361)), 720))


def power_spectrum_fft(spark, sf_dir):
    return _bins(spectrum.fft_series(X.month(spark, sf_dir)))


def power_spectrum_blocked(spark, sf_dir):
    return _bins(spectrum.fft_blocked(X.month(spark, sf_dir), 720, 24))


def harmonic_series(spark, sf_dir):
    return r6(spectrum.harmonics(spectrum.fft_series(X.month(spark, sf_dir)), 720, 30), "amplitude", "phase")


def fundamental_period(spark, sf_dir):
    """Planted periods and the aperiodic control: F2 24, F4 24, F1 null, F3 7."""
    out = []
    for name, s, n, trend in (
        ("month", X.month(spark, sf_dir), 720, 168),
        ("year", X.year(spark, sf_dir), 8760, 168),
        ("raw", series.fill_gaps(X.hourly(spark, sf_dir), 0, 719).withColumn("y", F.col("y_filled")), 720, 168),
        ("weekly", X.weekly(spark, sf_dir), 2499, 28),
    ):
        out.append(pipelines.period_of(s.select("series_id", "tick", "y"), n, trend).select(F.lit(name).alias("fixture"), "period_ticks"))
    return _union(out)


def period_rules(spark, sf_dir):
    """Every rule on the month, with and without the trend removed."""
    s = X.month(spark, sf_dir)
    out = []
    for how in ("running", "mean", "none"):
        f = spectrum.fft_series(spectrum.detrended(s, how))
        for rule in ("descend", "second_peak", "lowest_share", "max_power"):
            out.append(spectrum.fundamental(f, 720, rule).select(F.lit(how).alias("trend"), F.lit(rule).alias("rule"), "period_ticks", "power_ratio"))
    return _union(out)


def period_ladder(spark, sf_dir):
    return spectrum.period_ladder(X.month(spark, sf_dir), 720)


def period_sensitivity(spark, sf_dir):
    return spectrum.period_sensitivity(X.year(spark, sf_dir), 1000, 8760, 730, 8760)


def window_periods(spark, sf_dir):
    return spectrum.window_periods(X.year(spark, sf_dir), 730)


def window_membership(spark, sf_dir):
    windows = spark.range(12).select((F.col("id") * 50).alias("lo"), (F.col("id") * 50 + 120).alias("hi"), F.col("id").alias("draw"))
    s = X.month(spark, sf_dir)
    hit = s.join(F.broadcast(windows), (F.col("tick") >= F.col("lo")) & (F.col("tick") < F.col("hi")))
    return r6(hit.groupBy("draw").agg(F.count("*").alias("n"), F.max("y").alias("most")), "most")


# --- similarity, covers, thresholds ------------------------------------------------------------------------------


def _month_vectors(spark, sf_dir):
    return portraits.vectors(_slots(X.month(spark, sf_dir)), ["series_id", "slot"])


def similarity_pairs(spark, sf_dir):
    return r6(similarity.pairs(_month_vectors(spark, sf_dir)).select("a", "b", "dist"), "dist")


def similarity_edges(spark, sf_dir):
    return similarity.edges(_month_vectors(spark, sf_dir), 3.3).select("a", "b")


def similarity_edges_grid(spark, sf_dir):
    return similarity.edges(_month_vectors(spark, sf_dir), 3.3, method="grid").select("a", "b")


def graph_degrees(spark, sf_dir):
    e = similarity.edges(_month_vectors(spark, sf_dir), 3.3)
    return e.select(F.explode(F.array("a", "b")).alias("slot")).groupBy("slot").agg(F.count("*").alias("degree"))


def topk_similar_pairs(spark, sf_dir):
    p = similarity.pairs(_month_vectors(spark, sf_dir)).select("a", "b", F.round("dist", 6).alias("dist"))
    return p.orderBy("dist", "a", "b").limit(10)


def cover_greedy(spark, sf_dir):
    return cliquecover.greedy(_month_vectors(spark, sf_dir), 3.3).select("slot", "vp_id")


def cover_variants(spark, sf_dir):
    v = _month_vectors(spark, sf_dir)
    out = [
        cliquecover.greedy(v, 3.3, degree=d, order=o).groupBy().agg(F.countDistinct("vp_id").alias("n_groups")).select(F.lit(d).alias("degree"), F.lit(o).alias("neighbours"), "n_groups")
        for d in ("residual", "static")
        for o in ("id", "degree", "nearest")
    ]
    return _union(out)


def cover_exact(spark, sf_dir):
    return cliquecover.exact(_month_vectors(spark, sf_dir), 3.3).select("slot", "vp_id")


def cover_exact_violations(spark, sf_dir):
    v = _month_vectors(spark, sf_dir)
    return cliquecover.violations(cliquecover.exact(v, 3.3), v, 3.3)


def greedy_exact_ratio(spark, sf_dir):
    """Groups of the greedy cover over those of the least one."""
    v = _month_vectors(spark, sf_dir)
    n = [f(v, 3.3).groupBy("series_id").agg(F.countDistinct("vp_id").alias(name)) for f, name in ((cliquecover.greedy, "greedy"), (cliquecover.exact, "exact"))]
    return n[0].join(n[1], "series_id").withColumn("ratio", F.col("greedy") / F.col("exact"))


def cover_rounds(spark, sf_dir):
    v = _month_vectors(spark, sf_dir)
    return cliquecover.greedy_rounds(v.select(F.col("slot").alias("v")), similarity.edges(v, 3.3)).select("v", "seed")


def cover_violations(spark, sf_dir):
    v = _month_vectors(spark, sf_dir)
    return cliquecover.violations(cliquecover.greedy(v, 3.3), v, 3.3)


def cover_rounds_agree(spark, sf_dir):
    """Counts vertices whose group differs between the sequential and the parallel cover, lost ones included."""
    v = _month_vectors(spark, sf_dir)
    one = cliquecover.greedy(v, 3.3)
    two = cliquecover.greedy_rounds(v.select(F.col("slot").alias("v")), similarity.edges(v, 3.3), ties="id")
    both = one.join(two, one["slot"] == two["v"], "full_outer")
    least = both.withColumn("first", F.min("slot").over(Window.partitionBy("vp_id"))).withColumn("other", F.min("v").over(Window.partitionBy("seed")))
    return least.agg(F.count_if(~F.coalesce(F.col("first") == F.col("other"), F.lit(False)) | F.col("slot").isNull() | F.col("v").isNull()).alias("differences"))


def cover_rounds_path(spark, sf_dir):
    """The parallel cover of a path of 1 000 vertices: those not covered once, and pairs in a group without an edge."""
    n = 1000
    edges = spark.range(n - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    groups = cliquecover.greedy_rounds(spark.range(n).withColumnRenamed("id", "v"), edges)
    size = groups.groupBy("seed").agg(F.count("*").alias("n"), F.max("v").alias("hi"), F.min("v").alias("lo"))
    bad = size.agg(F.count_if((F.col("n") > 2) | (F.col("hi") - F.col("lo") != F.col("n") - 1)).alias("not_cliques"))
    return groups.agg((F.lit(n) - F.countDistinct("v") + F.count("v") - F.countDistinct("v")).alias("not_once")).crossJoin(bad)


def threshold_curve(spark, sf_dir):
    s = _slots(X.month(spark, sf_dir))
    return threshold.sweep(s, portraits.vectors(s, ["series_id", "slot"])).drop("series_id")


def elbow_choice(spark, sf_dir):
    s = _slots(X.month(spark, sf_dir))
    curve = threshold.sweep(s, portraits.vectors(s, ["series_id", "slot"]))
    out = [
        threshold.elbow(curve, rule, score).select(F.lit(rule).alias("rule"), F.lit(score).alias("score"), "n_groups", "s0")
        for rule in ("chord", "second_diff")
        for score in ("score_literal", "score_distance")
    ]
    out.append(threshold.elbow(curve, "fixed_n", fixed=6).select(F.lit("fixed_n").alias("rule"), F.lit("6").alias("score"), "n_groups", "s0"))
    return _union(out)


def landscape_curve(spark, sf_dir):
    s = _slots(X.year(spark, sf_dir))
    return threshold.sweep(s.select("series_id", "period_ix", "y"), landscape.block_vectors(s), "period_ix").drop("series_id")


def separation_fixed(spark, sf_dir):
    g = portraits.vectors(banded(_slots(X.month(spark, sf_dir))), SMALL)
    return r6(threshold.separation(g).select("score_literal", "score_distance"), "score_literal", "score_distance")


def block_vectors(spark, sf_dir):
    return r6(landscape.block_vectors(_slots(X.year(spark, sf_dir))).select("period_ix", "theta", "mad", "n"), "theta", "mad")


def virtual_landscapes(spark, sf_dir):
    s = _slots(X.year(spark, sf_dir))
    return _union([landscape.build_virtual(s, n).groupBy("vld_id").agg(F.count("*").alias("periods")).withColumn("asked", F.lit(n)) for n in (5, 7, 10)])


def landscape_cover_violations(spark, sf_dir):
    """Periods merged at a threshold: pairs of a group below it, periods not covered once."""
    s = _slots(X.year(spark, sf_dir))
    found = landscape.build_virtual(s, s0=2.0)
    return cliquecover.violations(found, landscape.block_vectors(s), 2.0, "period_ix", "vld_id")


def landscape_portrait_violations(spark, sf_dir):
    """Slots merged at a threshold inside each merged landscape: the same two counts, each landscape a series."""
    staged = landscape.attach(_slots(X.year(spark, sf_dir)), landscape.build_virtual(_slots(X.year(spark, sf_dir)), 7))
    staged = staged.withColumn("series_id", F.concat_ws(":", "series_id", "vld_id"))
    v = portraits.vectors(staged, ["series_id", "slot"])
    return cliquecover.violations(cliquecover.greedy(v, 3.3), v, 3.3)


def learned_map_agrees(spark, sf_dir):
    """The map that the elbow pipeline learns against the greedy cover at the elbow's threshold: slots that differ."""
    s = _slots(X.month(spark, sf_dir))
    v = portraits.vectors(s, ["series_id", "slot"])
    at = threshold.elbow(threshold.sweep(s, v)).first().s0
    one = pipelines.virtual_portraits(s, ["series_id"])
    two = cliquecover.greedy(v, at).select(F.col("slot").alias("v"), F.col("vp_id").alias("g"))
    both = one.join(two, one["slot"] == two["v"], "full_outer")
    return both.agg(F.count_if(~F.coalesce(F.col("vp_id") == F.col("g"), F.lit(False))).alias("differences"))


def _recheck(spark, flagged: DataFrame, by: str, rows: int) -> DataFrame:
    """Boxplot flags of a learned map against plain SQL that takes the map as its table: flags that differ, rows lost."""
    return spark.sql(
        f"with q as (select {by}, percentile(y, 0.25) q1, percentile(y, 0.75) q3 from {{f}} group by {by}) "
        "select count_if(f.is_outlier <> (f.y < q1 - 1.5D * (q3 - q1) or f.y > q3 + 1.5D * (q3 - q1))) as flags_differ, "
        f"cast({rows} as bigint) - count(distinct f.tick) as ticks_lost, count_if(f.vp_id is null) as without_group from {{f}} f join q using ({by})",
        f=flagged,
    )


def learned_small_consistent(spark, sf_dir):
    return _recheck(spark, pipelines.stationary(X.month(spark, sf_dir), 24, "iqr"), "vp_id", 720)


def learned_large_consistent(spark, sf_dir):
    return _recheck(spark, pipelines.nonstationary(X.year(spark, sf_dir), 24, "iqr", 7), "vld_id, vp_id", 8760)


def stationarity_route(spark, sf_dir):
    out = [landscape.route(X.month(spark, sf_dir), 24).withColumn("fixture", F.lit("month")), landscape.route(X.year(spark, sf_dir), 24).withColumn("fixture", F.lit("year"))]
    return r6(_union(out).select("fixture", "level_spread", "route"), "level_spread")


# --- fences, detection, repair -----------------------------------------------------------------------------------


def fences_normal(spark, sf_dir):
    return r6(fences.normal(banded(_slots(X.month(spark, sf_dir))), SMALL).select("vp_id", "n", "lo", "hi"), "lo", "hi")


def fences_normal_literal(spark, sf_dir):
    return r6(fences.normal(banded(_slots(X.month(spark, sf_dir))), SMALL, estimator="literal").select("vp_id", "n", "lo", "hi"), "lo", "hi")


def fences_normal_moments(spark, sf_dir):
    return r6(fences.normal(banded(_slots(X.month(spark, sf_dir))), SMALL, estimator="moments").select("vp_id", "n", "lo", "hi"), "lo", "hi")


def fences_boxplot(spark, sf_dir):
    return r6(fences.boxplot(banded(_slots(X.month(spark, sf_dir))), SMALL).select("vp_id", "n", "lo", "hi"), "lo", "hi")


def fences_boxplot_hinge(spark, sf_dir):
    return r6(fences.boxplot(banded(_slots(X.month(spark, sf_dir))), SMALL, quartile="hinge").select("vp_id", "n", "lo", "hi"), "lo", "hi")


def fences_gamma(spark, sf_dir):
    return fences.gamma(banded(_slots(X.month(spark, sf_dir))), SMALL).select("vp_id", "n", "lo", "hi", "centre", "model")


def fences_gamma_centres(spark, sf_dir):
    """Both readings of the gamma's replacement value: shape times scale, and their quotient."""
    rows = banded(_slots(X.month(spark, sf_dir)))
    a, b = (fences.gamma(rows, SMALL, replacement=r).select("vp_id", F.col("centre").alias(r)) for r in ("mean", "ratio"))
    return a.join(b, "vp_id").select("vp_id", F.round("mean", 6).alias("mean"), F.round("ratio", 3).alias("ratio"))


def own_strategy(spark, sf_dir):
    """A user's own fences: the outer twentieths of each group."""

    def tails(rows: DataFrame, by: list[str]) -> DataFrame:
        q = F.percentile("y", F.array(F.lit(0.05), F.lit(0.95)))
        e = rows.groupBy(*by).agg(q.alias("q"), F.count("*").alias("n"), F.avg("y").alias("centre"))
        return e.select(*by, "n", F.col("q")[0].alias("lo"), F.col("q")[1].alias("hi"), "centre", F.lit("tails").alias("model"))

    fences.register("tails", tails)
    return _flags(_small(spark, sf_dir, "tails"))


def fence_fit_check_gamma(spark, sf_dir):
    clean = banded(_slots(X.month(spark, sf_dir))).where("not is_polluted")
    return fences.fit_check(clean, SMALL, model="gamma").select("vp_id", "n", "distance", "count_statistic")


def fence_params(spark, sf_dir):
    """Fences of two models as one map of structs a group."""
    rows = banded(_slots(X.month(spark, sf_dir)))
    both = fences.boxplot(rows, SMALL).unionByName(fences.normal(rows, SMALL))
    entry = F.struct("model", F.struct("lo", "hi"))
    held = both.groupBy("vp_id").agg(F.map_from_entries(F.collect_list(entry)).alias("params"))
    told = held.select("vp_id", F.size(F.map_keys("params")).alias("models"), F.col("params")["iqr"]["lo"].alias("iqr_lo"), F.col("params")["normal"]["hi"].alias("normal_hi"))
    return r6(told, "iqr_lo", "normal_hi")


def join_fences_broadcast(spark, sf_dir):
    rows = banded(_slots(X.month(spark, sf_dir)))
    f = fences.boxplot(rows, SMALL).select("vp_id", "lo", "hi")  # four rows
    return _flags(rows.join(F.broadcast(f), "vp_id").withColumn("is_outlier", (F.col("y") < F.col("lo")) | (F.col("y") > F.col("hi"))))


def join_sort_merge(spark, sf_dir):
    rows = banded(_slots(X.month(spark, sf_dir)))
    f = fences.boxplot(rows, SMALL).select("vp_id", "lo", "hi").hint("merge")
    return _flags(rows.join(f, "vp_id").withColumn("is_outlier", (F.col("y") < F.col("lo")) | (F.col("y") > F.col("hi"))))


def fences_auto(spark, sf_dir):
    return r6(fences.auto(_slots(by_month(X.year(spark, sf_dir))), ["series_id", "vld_id", "slot"]).select("vld_id", "slot", "n", "lo", "hi", "model"), "lo", "hi")


def fence_fit_check(spark, sf_dir):
    clean = banded(_slots(X.month(spark, sf_dir))).where("not is_polluted")
    return fences.fit_check(clean, SMALL).select("vp_id", "n", "distance", "count_statistic")


def severity_classes(spark, sf_dir):
    told = fences.severity(banded(_slots(X.month(spark, sf_dir))), SMALL)
    return told.groupBy("vp_id", "severity").agg(F.count("*").alias("n"))


def small_detect_normal(spark, sf_dir):
    return _flags(_small(spark, sf_dir, "normal"))


def small_detect_gamma(spark, sf_dir):
    return _flags(_small(spark, sf_dir, "gamma"))


def small_detect_iqr(spark, sf_dir):
    return _flags(_small(spark, sf_dir, "iqr"))


def small_scores(spark, sf_dir):
    return _union([_score(_small(spark, sf_dir, m), m) for m in ("normal", "iqr", "gamma")])


def large_detect_normal(spark, sf_dir):
    return _flags(_large(spark, sf_dir, "normal"))


def large_detect_gamma(spark, sf_dir):
    return _flags(_large(spark, sf_dir, "gamma"))


def large_detect_iqr(spark, sf_dir):
    return _flags(_large(spark, sf_dir, "iqr"))


def large_scores(spark, sf_dir):
    return _union([_score(_large(spark, sf_dir, m), m) for m in ("normal", "iqr", "gamma")])


def flagged_points(spark, sf_dir):
    return r6(_small(spark, sf_dir, "iqr").where("is_outlier").select("tick", "slot", "y", "lo", "hi"), "y", "lo", "hi")


def learned_small_scores(spark, sf_dir):
    """The month with merged slots by the elbow: three strategies, the smoother inside groups, the smoother at each df."""
    s = X.month(spark, sf_dir)
    out = [_score(pipelines.stationary(s, 24, m), m) for m in ("normal", "gamma", "iqr")]
    slotted = _slots(s)
    grouped = slotted.join(pipelines.virtual_portraits(slotted, ["series_id"]), ["series_id", "slot"])
    out.append(_score(smoother.fit_in_groups(grouped, 68), "smoother in portraits 68"))
    out += [_score(smoother.detect(smoother.fit(s, df), df), f"smoother {df}") for df in DF_SMALL]
    return _union(out)


def learned_large_scores(spark, sf_dir):
    """The year with 5, 7 and 10 merged landscapes and three strategies each, beside the smoother."""
    s = X.year(spark, sf_dir)
    out = [_score(pipelines.nonstationary(s, 24, m, n), f"{n} {m}") for n in (5, 7, 10) for m in ("normal", "gamma", "iqr")]
    out += [_score(smoother.detect(smoother.fit(s, df), df), f"smoother {df}") for df in (100, 2000, 2815)]
    return _union(out)


def learned_mild_scores(spark, sf_dir):
    s = X.year(spark, sf_dir, X.MILD)
    out = [_score(pipelines.stationary(s, 24, m), f"direct {m}") for m in ("normal", "gamma", "iqr")]
    out += [_score(pipelines.nonstationary(s, 24, m, 10), f"10 {m}") for m in ("normal", "gamma", "iqr")]
    return _union(out)


def ablations(spark, sf_dir):
    """One group for all, slots without merging, and the year without merged landscapes."""
    m, y = X.month(spark, sf_dir), X.year(spark, sf_dir)
    out = [
        _score(pipelines.landscape_only(m, "iqr"), "month landscape only"),
        _score(pipelines.stationary(m, 24, "iqr", s0=float("inf")), "month basic portraits"),
        _score(pipelines.stationary(m, 24, "normal", estimator="literal"), "month normal unscaled"),
        _score(pipelines.stationary(y, 24, "iqr"), "year without landscapes"),
    ]
    return _union(out)


def ablation_fixed(spark, sf_dir):
    """Ablations on fixed maps: one group for all, each slot alone, an unscaled MAD, the year by bands alone."""
    m, y = _slots(X.month(spark, sf_dir)), _slots(X.year(spark, sf_dir))
    bands = banded(m)
    out = [
        _score(cleanse.detect(m, fences.boxplot(m, ["series_id"]), ["series_id"]), "one group"),
        _score(cleanse.detect(m, fences.boxplot(m, ["series_id", "slot"]), ["series_id", "slot"]), "basic portraits"),
        _score(cleanse.detect(bands, fences.normal(bands, SMALL, estimator="literal"), SMALL), "normal unscaled"),
        _score(cleanse.detect(banded(y), fences.boxplot(banded(y), SMALL), SMALL), "year without landscapes"),
    ]
    return _union(out)


def macro_scores(spark, sf_dir):
    return r6(metrics.macro_scores(_small(spark, sf_dir, "iqr"), SMALL), "accuracy", "precision", "recall", "f_measure")


def polluted_regions(spark, sf_dir):
    return metrics.regions(X.year(spark, sf_dir), "is_polluted").select("first_tick", "last_tick")


def region_scores(spark, sf_dir):
    return r6(metrics.region_scores(_small(spark, sf_dir, "iqr")), "precision", "recall", "f_measure")


def label_scores(spark, sf_dir):
    """Boxplot fences on n_chars by language against the quality labels: the measures on real 0/1 labels."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "lang", F.col("n_chars").cast("double").alias("y"))
    told = docs.join(read_table(spark, sf_dir, "labels"), "doc_id").withColumn("is_polluted", F.col("quality") == 0)
    return _score(cleanse.detect(told, fences.boxplot(told, ["lang"]), ["lang"], fence_rows=10), "length by language")


def strategy_overlap(spark, sf_dir):
    a = _small(spark, sf_dir, "normal").where("is_outlier").select("tick")
    b = _small(spark, sf_dir, "iqr").where("is_outlier").select("tick")
    return a.intersect(b)


def strategy_difference(spark, sf_dir):
    a = _small(spark, sf_dir, "normal").where("is_outlier").select("tick")
    b = _small(spark, sf_dir, "iqr").where("is_outlier").select("tick")
    return a.exceptAll(b)


def impute_missing(spark, sf_dir):
    full = _slots(series.fill_gaps(X.hourly(spark, sf_dir), 0, 719, default=None))
    medians = portraits.vectors(full, ["series_id", "slot"])
    return r6(cleanse.impute(full, medians, ["series_id", "slot"]).select("tick", "was_missing", "y_clean"), "y_clean")


def replaced_values(spark, sf_dir):
    return r6(cleanse.replace(_small(spark, sf_dir, "iqr")).where("is_outlier").select("tick", "y", "y_clean"), "y", "y_clean")


def replaced_median(spark, sf_dir):
    flagged = _small(spark, sf_dir, "iqr").withColumn("median", F.median("y").over(Window.partitionBy(*SMALL)))
    return r6(cleanse.replace(flagged, "median").where("is_outlier").select("tick", "y_clean"), "y_clean")


def cleanse_defaults(spark, sf_dir):
    """From raw hours to clean ones in one call: gaps as zero, fences by slot, outliers replaced."""
    told = cleanse.run(X.hourly(spark, sf_dir), 24, 0, 719)
    return r6(told.select("tick", "was_missing", "is_outlier", "y_clean"), "y_clean")


def imputation_error(spark, sf_dir):
    return r6(metrics.imputation_error(cleanse.replace(_small(spark, sf_dir, "iqr"))), "mae_clean", "mae_polluted")


def review_loop(spark, sf_dir):
    flagged = _small(spark, sf_dir, "iqr")
    verdicts = flagged.where("is_outlier and tick % 2 = 0").select("series_id", "tick", F.lit("replace").alias("verdict"))
    exempt = spark.range(1).select(F.lit("all").alias("series_id"), F.lit(100).alias("lo_tick"), F.lit(300).alias("hi_tick"))
    told = cleanse.review(flagged, verdicts, exempt)
    return told.where("is_outlier").groupBy("verdict").agg(F.count("*").alias("n"))


def smoother_fit(spark, sf_dir):
    return r6(smoother.fit(X.month(spark, sf_dir), 148).select("tick", "y_hat"), "y_hat")


def smoother_dense(spark, sf_dir):
    return smoother.fit(X.month(spark, sf_dir), 148, dense=True).select("tick", "y_hat")


def smoother_penalised(spark, sf_dir):
    f = smoother.fit_penalised(X.month(spark, sf_dir), 68.0)
    return _score(smoother.detect(f, 68), "penalised 68")


def smoother_training(spark, sf_dir):
    s = X.month(spark, sf_dir)
    return _union([smoother.train(s, list(DF_SMALL), by).withColumn("by", F.lit(by)) for by in ("gcv", "f_measure")]).drop("series_id")


def smoother_underfit(spark, sf_dir):
    s = X.year(spark, sf_dir)
    return _union([_score(smoother.detect(smoother.fit(s, df), df), f"df {df}") for df in (100, 200)])


def smoother_dense_agrees(spark, sf_dir):
    """Fitted values of the banded and the dense solution that differ."""
    s = X.month(spark, sf_dir)
    a = smoother.fit(s, 148).select("tick", "y_hat")
    b = smoother.fit(s, 148, dense=True).select("tick", F.col("y_hat").alias("d"))
    return a.join(b, "tick", "full_outer").agg(F.count_if(~F.coalesce(F.abs(F.col("y_hat") - F.col("d")) < 1e-4, F.lit(False))).alias("differ"))


def smoother_overfit(spark, sf_dir):
    s = X.month(spark, sf_dir)
    return _union([_score(smoother.detect(smoother.fit(s, df), df), f"df {df}") for df in (318, 480, 640)])


def smoother_local_view(spark, sf_dir):
    """Weeks of the year: labelled points that a stiff fit misses, and plain points that a flexible one bends away from."""
    s, out = X.year(spark, sf_dir), []
    for df in (100, 200):
        told = smoother.detect(smoother.fit(s, df), df).withColumn("week", F.floor(F.col("tick") / 168))
        per = told.groupBy("week").agg(
            F.count_if(F.col("is_polluted") & ~F.col("is_outlier")).alias("missed"),
            F.count_if(~F.col("is_polluted") & F.col("is_outlier")).alias("wrongly_flagged"),
            F.count_if(~F.col("is_polluted") & (F.abs(F.col("y_hat") - F.col("y_true")) > 0.5 * F.col("y_true"))).alias("bent_away"),
        )
        out.append(per.withColumn("df", F.lit(df)))
    return _union(out)


def flagged_points_year(spark, sf_dir):
    """The picture of the year: gamma fences in seven merged landscapes."""
    told = pipelines.nonstationary(X.year(spark, sf_dir), 24, "gamma", 7)
    return told.where("is_outlier").select("tick", "vld_id", "vp_id", "y", "lo", "hi", "is_polluted")


def outage_recall(spark, sf_dir):
    s = X.outage(spark, sf_dir)
    a = metrics.outage_recall(pipelines.nonstationary(s, 24, "iqr", 7), 3920, 3975).withColumn("method", F.lit("portrait iqr 7"))
    c = metrics.outage_recall(pipelines.nonstationary(s, 24, "iqr", 7, least=5), 3920, 3975).withColumn("method", F.lit("portrait iqr 7, small groups absorbed"))
    b = metrics.outage_recall(smoother.detect(smoother.fit(s, 100), 100), 3920, 3975).withColumn("method", F.lit("smoother 100"))
    return _union([a, c, b]).drop("series_id")


def holiday_recall(spark, sf_dir):
    s = X.holidays(spark, sf_dir)
    absorbed = _score(pipelines.nonstationary(s, 24, "iqr", 7, least=5), "portrait iqr 7, small groups absorbed")
    return _union([_score(pipelines.nonstationary(s, 24, "iqr", 7), "portrait iqr 7"), absorbed, _score(smoother.detect(smoother.fit(s, 100), 100), "smoother 100")])


def hidden_outliers(spark, sf_dir):
    return _score(pipelines.stationary(X.hidden(spark, sf_dir), 24, "iqr"), "hidden")


def negative_control(spark, sf_dir):
    """The raw hourly series: no period, so that the method declines."""
    s = series.fill_gaps(X.hourly(spark, sf_dir), 0, 719).select("series_id", "tick", F.col("y_filled").alias("y"))
    return pipelines.period_of(s, 720).select("period_ticks")


def fleet_vectors(spark, sf_dir):
    return r6(portraits.vectors(_slots(X.fleet(spark, sf_dir)), ["series_id", "slot"]), "theta", "mad")


def fleet_scores(spark, sf_dir):
    return r6(metrics.scores(pipelines.stationary(X.fleet(spark, sf_dir), 24, "iqr"), ["series_id"]), "accuracy", "precision", "recall", "f_measure")


def fleet_periods(spark, sf_dir):
    return pipelines.period_of(X.fleet(spark, sf_dir), 720).select("series_id", "period_ticks")


# --- surrounding operators ---------------------------------------------------------------------------------------


def quartiles(spark, sf_dir):
    q = F.percentile("y", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)))
    g = _slots(X.month(spark, sf_dir)).groupBy("slot").agg(q.alias("q"))
    return r6(g.select("slot", F.col("q")[0].alias("q1"), F.col("q")[1].alias("q2"), F.col("q")[2].alias("q3")), "q1", "q2", "q3")


def distinct_users_hourly(spark, sf_dir):
    e = read_table(spark, sf_dir, "events")
    return e.groupBy(F.hour("ts").alias("hour")).agg(F.countDistinct("user_id").alias("users"))


def load_rollup(spark, sf_dir):
    li = read_table(spark, sf_dir, "lineitem").select("l_suppkey", "l_quantity")
    su = read_table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    na = read_table(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey")
    re = read_table(spark, sf_dir, "region").select("r_regionkey", "r_name")
    j = li.join(su, F.col("l_suppkey") == F.col("s_suppkey")).join(F.broadcast(na), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(re), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.rollup("r_name", "n_name").agg((F.sum(F.round(F.col("l_quantity").cast("double") * 100).cast("bigint")) / 100.0).alias("load"), F.count("*").alias("n"))


def load_cube(spark, sf_dir):
    e = read_table(spark, sf_dir, "events").withColumn("hour", F.hour("ts"))
    return e.cube("event_type", "hour").agg((F.sum(F.round(F.col("value") * 100).cast("bigint")) / 100.0).alias("load"))


def top_deviation(spark, sf_dir):
    s = _slots(X.month(spark, sf_dir))
    told = s.withColumn("theta", F.median("y").over(Window.partitionBy("series_id", "slot"))).withColumn("away", F.round(F.abs(F.col("y") - F.col("theta")), 6))
    rank = F.row_number().over(Window.partitionBy("slot").orderBy(F.desc("away"), "tick"))
    return told.withColumn("place", rank).where("place <= 2").select("slot", F.col("place").cast("bigint").alias("place"), "tick", "away")


def rolling_slot_mean(spark, sf_dir):
    w = Window.partitionBy("series_id", "slot").orderBy("period_ix").rowsBetween(-6, 0)
    return r6(_slots(X.month(spark, sf_dir)).select("tick", F.avg("y").over(w).alias("mean7")), "mean7")


def spectrum_peaks(spark, sf_dir):
    w = Window.partitionBy("series_id").orderBy("k")
    s = spectrum.dft_bins(X.month(spark, sf_dir), list(range(361)), 720)
    s = s.select("series_id", "k", F.round("power", 4).alias("power"))
    s = s.withColumn("b", F.lag("power", 1, -1.0).over(w)).withColumn("a", F.lead("power", 1, -1.0).over(w))
    return s.where("power > b and power > a and power > 100").select("k")


def peak_rank(spark, sf_dir):
    """Slots by their median: the ranking functions beside each other."""
    w = Window.partitionBy("series_id").orderBy(F.desc("top"), "slot")
    v = _month_vectors(spark, sf_dir).withColumn("top", F.round("theta", 6))
    return v.select(
        "slot",
        F.rank().over(w).cast("bigint").alias("place"),
        F.dense_rank().over(w).cast("bigint").alias("dense_place"),
        F.ntile(4).over(w).cast("bigint").alias("quarter"),
        F.round(F.percent_rank().over(w), 6).alias("share_before"),
    )


def sampled_vectors(spark, sf_dir):
    """Vectors of a fixed three tenths of the ticks, chosen by arithmetic on the tick."""
    s = _slots(X.month(spark, sf_dir)).where(F.pmod(F.col("tick") * 7919 + 13, F.lit(1000)) < 300)
    return r6(portraits.vectors(s, ["series_id", "slot"]).select("slot", "n", "theta", "mad"), "theta", "mad")


def observed_counts(spark, sf_dir):
    """Counts that a run of the plan observes on its way, without a second pass."""
    seen = Observation("series")
    told = X.month(spark, sf_dir).observe(seen, F.count(F.lit(1)).alias("n"), F.count_if("is_polluted").alias("polluted"), F.max("tick").alias("last"))
    told.write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["n"], seen.get["polluted"], seen.get["last"])], "n bigint, polluted bigint, last bigint")


def asof_fences(spark, sf_dir):
    """Fence version in force at each sample: versions every five days, by union and last non-null value a series."""
    s = X.month(spark, sf_dir).select("series_id", "tick", F.lit(None).cast("bigint").alias("version"))
    v = spark.range(6).select(F.lit("all").alias("series_id"), (F.col("id") * 120 + 7).alias("tick"), F.col("id").alias("version"))
    w = Window.partitionBy("series_id").orderBy("tick", F.col("version").isNull()).rowsBetween(Window.unboundedPreceding, 0)
    told = s.unionByName(v).withColumn("in_force", F.last("version", True).over(w))
    return told.where("version is null").select("tick", "in_force")


def calendar_slots(spark, sf_dir):
    o = read_table(spark, sf_dir, "orders")
    return o.groupBy(F.dayofweek("o_orderdate").alias("weekday"), F.quarter("o_orderdate").alias("season")).agg(F.count("*").alias("n"))


def series_key(spark, sf_dir):
    e = read_table(spark, sf_dir, "events")
    return e.select(F.concat_ws(":", "event_type", F.lpad(F.col("user_id").cast("string"), 6, "0")).alias("series_key")).groupBy("series_key").agg(F.count("*").alias("n"))


def props_slot(spark, sf_dir):
    e = read_table(spark, sf_dir, "events")
    return e.groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n"))


def curve_array(spark, sf_dir):
    """One array a day and its peak by higher-order functions."""
    s = _slots(X.month(spark, sf_dir)).groupBy("period_ix").agg(F.transform(F.sort_array(F.collect_list(F.struct("slot", "y"))), lambda x: x["y"]).alias("day"))
    return r6(s.select("period_ix", F.array_max("day").alias("peak"), F.aggregate("day", F.lit(0.0), lambda a, x: a + x).alias("total")), "peak", "total")


def periodic_series_only(spark, sf_dir):
    s = X.fleet(spark, sf_dir)
    good = pipelines.period_of(s, 720).where("period_ticks is not null").select("series_id")
    return s.join(good, "series_id", "left_semi").groupBy("series_id").agg(F.count("*").alias("n"))


def sql_detect(spark, sf_dir):
    surface.register(spark)
    X.month(spark, sf_dir).createOrReplaceTempView("samples")
    return spark.sql(
        "with v as (select slot_of(tick, {r}) slot, median(y) theta from samples group by 1) "
        "select s.tick, round(s.y - v.theta, 6) away from samples s join v on slot_of(s.tick, {r}) = v.slot where abs(s.y - v.theta) > 0.5",
        r=24,
    )


def udtf_period_ticks(spark, sf_dir):
    """Every tick of the days that an event type spans, from the table function, and how many of them hold an event, a slot."""
    surface.register(spark)
    return spark.sql(
        "with h as (select event_type, tick, period_of_tick(tick, 24) day from {hours}), "
        "d as (select event_type, min(day) first, cast(max(day) - min(day) + 1 as int) days from h group by event_type), "
        "g as (select event_type, first * 24 + t.tick tick, t.slot from d, lateral period_ticks(d.days, 24) t) "
        "select g.event_type, slot, count(*) n, count(h.tick) n_held from g left join h on g.event_type <=> h.event_type and g.tick = h.tick group by g.event_type, slot",
        hours=series.regularise(read_table(spark, sf_dir, "events"), "ts", "value", "2024-01-01", 3600, "count", ["event_type"]),
    )


def asked_quantiles(spark, sf_dir):
    """Gamma quantiles of each event type's values at asked probabilities, by shape and scale of its own moments."""
    e = portraits.vectors(read_table(spark, sf_dir, "events"), ["event_type"], "value", "mean_sd")
    fine = (F.col("theta") > 0) & (F.col("mad") > 0)
    e = e.withColumns({"shape": F.when(fine, (F.col("theta") / F.col("mad")) ** 2), "scale": F.when(fine, F.col("mad") ** 2 / F.col("theta"))})
    e = e.withColumn("q", F.explode(F.array(*map(F.lit, (0.025, 0.5, 0.975)))))
    return r6(e.select("event_type", "q", F.nanvl(surface.gamma_quantile_of("q", "shape", "scale"), F.lit(None)).alias("value")), "value")


def udf_gamma_fence(spark, sf_dir):
    """Gamma quantiles of each slot of the month, by SQL functions alone: the fences and the middle."""
    surface.register(spark)
    return spark.sql(
        "with v as (select slot_of(tick, 24) slot, median(y) theta, 1.4826D * mad_of(collect_list(y)) mad from {samples} group by 1), "
        "g as (select slot, case when theta > 0 and mad > 0 then (theta / mad) * (theta / mad) end shape, case when theta > 0 and mad > 0 then mad * mad / theta end scale from v) "
        "select slot, q, round(nanvl(gamma_quantile_of(q, shape, scale), null), 6) value from g cross join values (0.025D), (0.5D), (0.975D) t(q)",
        samples=X.month(spark, sf_dir),
    )


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return small_detect_iqr(spark, sf_dir)


_SKIP = {"r6", "banded", "by_month", "flagship", "read_table"}
QUERIES = {
    name: fn for name, fn in list(globals().items()) if callable(fn) and not name.startswith("_") and name not in _SKIP and getattr(fn, "__module__", "") == __name__
}
