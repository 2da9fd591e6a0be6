"""Experiment workloads on the given tables: distributions, strata, sweeps, fronts, build costs."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.distance import l2sq
from ..functions.predicates import InRange
from ..operators import exact, graph, ivf, quantize, two_level
from ..sources import carriers
from ..sources.store import export_report, frame_bytes, read_report, shared_dir, written
from ..streaming.updates import relabel
from . import metrics, tune


def label_frequency(base: DataFrame) -> DataFrame:
    return base.select(F.explode("labels").alias("label")).groupBy("label").agg(F.count("*").alias("n"))


def size_histogram(base: DataFrame) -> DataFrame:
    return base.groupBy(F.size("labels").alias("size")).agg(F.count("*").alias("n"))


def group_histogram(base: DataFrame) -> DataFrame:
    return base.groupBy("labels").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("groups"))


def length_strata(queries: DataFrame) -> DataFrame:
    n = F.size("qlabels")
    return queries.groupBy(F.when(n <= 1, "short").when(n <= 3, "medium").otherwise("long").alias("stratum")).agg(F.count("*").alias("queries"))


def selectivity_strata(share: DataFrame, percents: tuple[int, ...] = (75, 50, 25, 1)) -> DataFrame:
    """Each query with the percentile (of passing rows) that it is nearest to; ties to the larger."""
    edges = share.agg(*(F.expr(f"percentile_disc({p / 100}) within group (order by passing)").alias(f"p{p}") for p in percents))  # one row
    near = share.join(F.broadcast(edges))
    best = F.array_min(F.array(*(F.struct(F.abs(F.col("passing") - F.col(f"p{p}")).alias("d"), F.lit(-p).alias("s")) for p in percents)))
    return near.select("qid", "passing", (-best["s"]).alias("stratum"))


def with_enough_truth(queries: DataFrame, base: DataFrame, of: str, k: int) -> DataFrame:
    """Queries with at least k passing rows."""
    return queries.join(metrics.selectivity(base, queries, of).where(F.col("passing") >= k).select("qid"), "qid")


def nested_sample(base: DataFrame, percent: int) -> DataFrame:
    """Growing percents give supersets."""
    return base.where(F.col("id") * 7919 % 1009 < 1009 * percent // 100)


def lattice_edges(base: DataFrame) -> DataFrame:
    """parent, child label sets of minimal inclusion. A parent meets only the groups that have its rarest label; the root meets all."""
    groups = written(base.select("labels").distinct(), "groups")
    flat = groups.select("labels", F.explode("labels").alias("label"))
    counts = flat.groupBy("label").count()
    rarest = flat.join(counts, "label").groupBy("labels").agg(F.min(F.struct("count", "label"))["label"].alias("label"))
    above = rarest.withColumnRenamed("labels", "parent").join(flat.withColumnRenamed("labels", "child"), "label").where((F.size("child") > F.size("parent")) & (F.size(F.array_except("parent", "child")) == 0))
    root = groups.where("size(labels) = 0").select(F.col("labels").alias("parent"))
    pairs = written(above.select("parent", "child").unionByName(root.join(F.broadcast(groups.where("size(labels) > 0").select(F.col("labels").alias("child"))))), "inclusions")
    through = pairs.alias("x").join(pairs.alias("y"), F.col("x.child") == F.col("y.parent")).select(F.col("x.parent").alias("parent"), F.col("y.child").alias("child")).distinct()
    return pairs.join(through, ["parent", "child"], "left_anti")


def lattice_reachable(base: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, labels, n: the groups that hold a query's set, by one superset join."""
    groups = base.groupBy("labels").agg(F.count("*").alias("n"))
    hits = exact.candidates(groups.withColumn("id", F.xxhash64("labels")), queries, "containment")
    return hits.select("qid", F.array_join("labels", ",").alias("labels"), "n")


def exact_rounds(base: DataFrame, queries: DataFrame, of: str, k: int, l0: int) -> DataFrame:
    """qid, rounds of doubling from l0 until k rows pass among the l nearest, in exact order. The k-th passing row comes from a search, and its position from a count."""
    last, total = written(exact.search(base, queries, of, k).where(F.col("rank") == k), "last"), base.count()
    need = queries.select("qid").where(F.lit(total > 0)).join(exact.positions(base, queries, last), "qid", "left").select("qid", F.coalesce("pos", F.lit(total)).alias("need"))
    return need.select("qid", F.when(F.col("need") <= l0, 1).otherwise(1 + F.ceil(F.log2(F.col("need") / l0))).cast("int").alias("rounds"))


def document_search(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """Retrieval with a combined predicate: same language, 500 to 8,000 characters, not marked toxic."""
    rows = carriers._documents(spark, sf_dir).select(F.col("doc_id").alias("id"), "lang", "n_chars", "toxic", carriers.letter_profile(F.col("text")).alias("vec"))
    held = F.coalesce(F.col("id") * 7919 % 1009 < 20, F.lit(False))
    queries = rows.where(held).select(F.col("id").alias("qid"), F.col("lang").alias("qlang"), F.col("vec").alias("qvec"))
    passing = rows.where(~held & F.col("n_chars").between(500, 8000) & (F.coalesce("toxic", F.lit(0)) == 0))
    hits = passing.join(exact.small(queries), F.col("lang") == F.col("qlang"))
    return exact.top_k(hits.select("qid", "id", l2sq(F.col("vec"), F.col("qvec")).alias("dist")), k)


def document_search_sql(k: int) -> str:
    from ..functions.distance import DISTANCE_SQL

    cte = carriers.carrier_sql("doc_attr", 1).split(", base as materialized")[0]
    return f"with {cte}, d as (select rows_.id, vec, lang, n_chars, toxic, coalesce(rows_.id*7919 % 1009 < 20, false) as q from rows_ join documents on doc_id = rows_.id left join labels l on l.doc_id = rows_.id), s as (select a.id as qid, b.id as id, {DISTANCE_SQL.replace('list_zip(vec, qvec)', 'list_zip(b.vec, a.vec)')} as dd from d a join d b on a.lang = b.lang where a.q and not b.q and b.n_chars between 500 and 8000 and coalesce(b.toxic, 0) = 0), r as (select *, row_number() over (partition by qid order by dd, id) as r from s) select qid::bigint as qid, r::int as rank, id::bigint as id, round(dd, 6) as dist from r where r <= {k}"


def order_search(spark: SparkSession, sf_dir: str, k: int, first: str = "1994-01-01", last: str = "1996-12-31") -> DataFrame:
    """Orders of a span of dates that share a supplier nation: the dates cut the base before any distance."""
    d = carriers.dataset(spark, sf_dir, "basket_nation", 1)
    dated = carriers.read(spark, sf_dir, "orders").where(InRange("o_orderdate", first, last).column(F.lit(None), F.lit(None))).select(F.col("o_orderkey").alias("id"))
    return exact.search(d.base.join(dated, "id", "left_semi"), d.queries, "overlap", k)


# Grids of the tuning and build workloads: two values for the parameters that matter most.
GRIDS: dict[str, dict[str, list[float]]] = {
    "postfilter": {"degree": [6, 12], "breadth": [16, 32]},
    "twohop": {"degree": [6, 12], "breadth": [16, 32]},
    "dense": {"degree": [8, 16], "gamma": [2, 4]},
    "lattice": {"degree": [6, 12], "cross": [2, 4]},
    "shared": {"degree": [6, 12], "alpha": [1.0, 1.2]},
    "stitched": {"sub_degree": [6, 12], "stitched_degree": [16, 32]},
    "fused": {"degree": [6, 12], "label_weight": [1.0, 4.0]},
}


def tuning_run(spark: SparkSession, sf_dir: str, method: str = "postfilter") -> DataFrame:
    """Representatives of a method's sub-boxes: their sample runs, and the seconds and bytes of their builds on the whole base.
    The fused graph is tuned on label vectors of fixed length, the others on sets."""
    fixed = method == "fused"
    d, values = carriers.dataset(spark, sf_dir, "emb_fixed4" if fixed else "emb_zipf", 4 if fixed else 1), GRIDS[method]
    base, queries = written(d.base, "base"), written(d.queries, "queries")
    scenarios = ["fixed"] if fixed else ["containment", "overlap"] if method == "postfilter" else ["containment"]
    runs, picks = tune.tune(method, base, queries, values, scenarios, breadths=[10, 40], share=0.5)
    built = []
    for config in tune.picked(method, picks, values):
        start = time.monotonic()
        index = graph.fit(base, method, dict(config.params))
        built.append((config.config_id, time.monotonic() - start, frame_bytes(index.nodes)))
    full = spark.createDataFrame(built, "config_id string, full_build_s double, full_bytes bigint")
    chosen = runs.join(F.broadcast(picks), ["subspace", "config_id"]).join(F.broadcast(full), "config_id")
    return chosen.select("subspace", "config_id", "scenario", "breadth", "recall", "qps", "dist_comps", "full_build_s", "full_bytes")


def tuning_baselines(spark: SparkSession, sf_dir: str, method: str = "twohop") -> DataFrame:
    """Runs on the whole base by way of tuning: none (defaults), sampled (the pick of sample runs, built in full), exhaustive (all settings)."""
    d, values = carriers.dataset(spark, sf_dir, "emb_zipf", 1), GRIDS[method]
    base, of, breadths = written(d.base, "base"), ["containment"], [10, 40]
    _, picks = tune.tune(method, base, d.queries, values, of, breadths=breadths, cuts=1)
    whole = written(tune.tune_exhaustive(method, base, d.queries, values, of, breadths=breadths), "runs").withColumn("way", F.lit("exhaustive"))
    none = tune.measure([tune.tune_none(method)], base, d.queries, of, 10, breadths).withColumn("way", F.lit("none"))
    sampled = whole.join(F.broadcast(picks.select("config_id")), "config_id", "left_semi").withColumn("way", F.lit("sampled"))
    return none.unionByName(sampled).unionByName(whole).select("way", "config_id", "scenario", "breadth", "recall", "qps", "build_s", "dist_comps")


def multi_label_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Label walks that start at one asked label against all of them: method, multi, recall, dist_comps a query."""
    d, rows = carriers.dataset(spark, sf_dir, "emb_zipf", 2), []
    base = written(d.base, "base")
    truth = written(exact.search(base, d.queries, "overlap", 10), "truth")
    for method in ("shared", "stitched"):
        index = graph.fit(base, method)
        for multi in (False, True):
            found = written(graph.raw_search(index, d.queries, "overlap", 10, breadth=40, multi=multi), "found")
            cost = graph.costs(found).agg(F.avg("dist_comps")).first()[0]
            rows.append((method, multi, metrics.recall(exact.rerank(found.where("id is not null"), base, d.queries, 10), truth, 10), cost))
    return spark.createDataFrame(rows, "method string, multi boolean, recall double, dist_comps double")


def update_runs(spark: SparkSession, sf_dir: str, methods: tuple[str, ...] = ("postfilter", "twohop", "dense", "shared", "stitched", "lattice")) -> DataFrame:
    """Every tenth row gets other labels: method, way (relabel keeps vectors and edges, rebuild fits anew), seconds, recall against the new labels."""
    d, rows = carriers.dataset(spark, sf_dir, "emb_zipf", 1), []
    base = written(d.base, "base")
    changed = written(base.where("id % 10 = 7").select("id", F.transform("labels", lambda a: a % 24 + 1).alias("labels")).withColumn("labels", F.array_sort("labels")), "changed")
    after = written(relabel(base, changed), "after")
    truth = written(exact.search(after, d.queries, "containment", 10), "truth")
    for method in methods:
        index = graph.fit(base, method)
        for way in ("relabel", "rebuild"):
            start = time.monotonic()
            new = graph.fit(after, method) if way == "rebuild" else replace(index, nodes=written(relabel(index.nodes, changed), "relabelled"))
            took = time.monotonic() - start
            rows.append((method, way, took, metrics.recall(graph.search(new, d.queries, "containment", 10, breadth=40, l0=40, restart=False), truth, 10)))
    return spark.createDataFrame(rows, "method string, way string, seconds double, recall double")


METHOD_RUNS = ("prefilter", "pq", "ivfpq", *graph.DEFAULTS, "two_level")
Search = Callable[[DataFrame, str, int, int], DataFrame]  # queries, scenario, k, breadth


def searcher(base: DataFrame, method: str) -> Search:
    """Fit a method once; its search takes one breadth, whatever the method calls it."""
    if method == "prefilter":
        return lambda asked, of, k, b: exact.search(base, asked, of, k)
    if method == "pq":
        codes = quantize.fit(base)
        return lambda asked, of, k, b: quantize.search(codes, asked, of, k, b)
    if method == "ivfpq":
        lists = ivf.fit(base)
        return lambda asked, of, k, b: ivf.search(lists, asked, of, k, probes=max(1, b // k))
    if method == "two_level":
        parts = two_level.fit(base)
        return lambda asked, of, k, b: two_level.search(parts, asked, k, probes=max(1, b // k))
    index = graph.fit(base, method)
    return lambda asked, of, k, b: graph.search(index, asked, of, k, breadth=b, l0=b, restart=False)


def point(find: Search, asked: DataFrame, n: int, truth: DataFrame, of: str, k: int, breadth: int) -> tuple[float, float]:
    """Recall and queries per second of one run, whose rows are written once."""
    found, qps = timed(find, asked, n, of, k, breadth)
    return metrics.recall(found, truth, k), qps


def timed(find: Search, asked: DataFrame, n: int, of: str, k: int, breadth: int) -> tuple[DataFrame, float]:
    start = time.monotonic()
    found = written(find(asked, of, k, breadth), "found")
    return found, n / max(time.monotonic() - start, 1e-9)


def overall(
    spark: SparkSession, sf_dir: str, carrier: str = "emb_zipf", scenarios: tuple[str, ...] = ("containment", "overlap", "equality"), k: int = 10, breadths: tuple[int, ...] = (10, 40), methods: tuple[str, ...] = METHOD_RUNS
) -> DataFrame:
    """Recall and throughput by method, scenario and breadth, with a mark for the front; queries have at least k passing rows.
    Equality asks for a row's whole set, the others for two of its labels. A method that doesn't support a scenario has no rows there."""
    from .advisor import supports

    rows, wide = [], {s: carriers.dataset(spark, sf_dir, carrier, None if s == "equality" else 2) for s in scenarios}
    base = written(wide[scenarios[0]].base, "base")
    asked = {s: written(with_enough_truth(d.queries, base, s, k), "asked") for s, d in wide.items()}
    many = {s: asked[s].count() for s in scenarios}
    truth, found = {s: written(exact.search(base, asked[s], s, k), "truth") for s in scenarios}, []
    for m in methods:
        wanted = [s for s in scenarios if many[s] and supports({"pq": "quantized"}.get(m, m), s)]
        find = searcher(base, m) if wanted else None
        for s in wanted:
            for b in breadths if m != "prefilter" else breadths[:1]:
                got, qps = timed(find, asked[s], many[s], s, k, b)
                rows.append((len(found), m, s, float(b), many[s], qps))
                found.append(got.select(F.lit(len(found)).alias("run"), F.lit(s).alias("scenario"), "qid", "id"))
    schema = "run int, method string, scenario string, breadth double, queries bigint, qps double"
    if not rows:
        return spark.createDataFrame([], schema.replace("run int, ", "") + ", recall double, on_front boolean")
    # recall of all runs in one pass: every query has k truths
    answers = reduce(DataFrame.unionByName, [truth[s].select(F.lit(s).alias("scenario"), "qid", "id") for s in scenarios])
    hits = reduce(DataFrame.unionByName, found).join(answers, ["scenario", "qid", "id"]).groupBy("run").agg(F.count("*").alias("hits"))
    share = F.coalesce("hits", F.lit(0)) / (k * F.col("queries"))
    runs = written(spark.createDataFrame(rows, schema).join(F.broadcast(hits), "run", "left").select("method", "scenario", "breadth", "queries", "qps", share.alias("recall")), "runs")
    front = metrics.pareto(runs, ["scenario"]).select("method", "scenario", "breadth", F.lit(True).alias("on_front"))
    return runs.join(front, ["method", "scenario", "breadth"], "left").withColumn("on_front", F.coalesce("on_front", F.lit(False)))


def thread_runs(spark: SparkSession, sf_dir: str, methods: tuple[str, ...] = ("postfilter", "lattice"), lanes: int = 4) -> DataFrame:
    """The same index asked by one task and by several, each with its part of the queries: method, way, lanes, found rows, qps."""
    d, rows = carriers.dataset(spark, sf_dir, "emb_zipf", 1), []
    base, queries = written(d.base, "base"), written(d.queries, "queries")
    n, key = queries.count(), "spark.sql.shuffle.partitions"
    usual = spark.conf.get(key)
    for m in methods:
        index = graph.fit(base, m)
        for way, cut in (("one", 1), ("several", lanes)):
            spark.conf.set(key, "1" if cut == 1 else usual)
            try:
                found, qps = timed(lambda asked, of, k, b: graph.raw_search(index, asked, of, k, breadth=b, l0=b, lanes=cut), queries, n, "containment", 10, 40)  # noqa: B023
            finally:
                spark.conf.set(key, usual)
            rows.append((m, way, cut, found.where("id is not null").count(), qps))
    return spark.createDataFrame(rows, "method string, way string, lanes int, found bigint, qps double")


def build_costs(spark: SparkSession, sf_dir: str, carrier: str = "emb_zipf", percents: tuple[int, ...] = (50, 100), methods: tuple[str, ...] = ("postfilter", "twohop", "dense", "shared", "stitched", "lattice")) -> DataFrame:
    """Build seconds and index bytes by method and share of the base, raw and scaled to 0..1 within a method."""
    d, rows = carriers.dataset(spark, sf_dir, carrier), []
    base = written(d.base, "base")
    for m in methods:
        for p in percents:
            start = time.monotonic()
            index = graph.fit(nested_sample(base, p), m)
            rows.append((m, p, time.monotonic() - start, frame_bytes(index.nodes)))
    runs = spark.createDataFrame(rows, "method string, percent int, build_s double, index_bytes bigint")
    return metrics.normalised(runs, ["build_s", "index_bytes"], ["method"])


# ------------------------------------------------------------------ one difficulty factor at a time

SWEEP_METHODS = ("prefilter", "ivfpq", "postfilter", "twohop", "lattice", "stitched")


def sweep(spark: SparkSession, variants: list[tuple[str, carriers.Dataset]], scenario: str, methods: tuple[str, ...] = SWEEP_METHODS, k: int | dict[str, int] = 10, breadth: int = 40) -> DataFrame:
    """setting, method, scenario, k, queries, recall, qps over variants of a dataset; queries keep at least k passing rows."""
    rows = []
    kept: dict[int, DataFrame] = {}  # a base that several settings share is derived once, and each method is fitted to it once
    fitted: dict[tuple[int, str], Search] = {}
    for setting, d in variants:
        own = k[setting] if isinstance(k, dict) else k
        base = kept[id(d.base)] = kept[id(d.base)] if id(d.base) in kept else written(d.base, "base")
        asked = written(with_enough_truth(d.queries, base, scenario, own), "queries")
        n = asked.count()
        truth = written(exact.search(base, asked, scenario, own), "truth")
        for m in methods if n else ():
            find = fitted[id(d.base), m] = fitted[id(d.base), m] if (id(d.base), m) in fitted else searcher(base, m)
            rows.append((setting, m, scenario, own, n, *point(find, asked, n, truth, scenario, own, max(own, breadth))))
    return spark.createDataFrame(rows, "setting string, method string, scenario string, k int, queries bigint, recall double, qps double")


def label_length_runs(spark: SparkSession, sf_dir: str, carrier: str = "doc_attr", scenario: str = "containment") -> DataFrame:
    """Short (1), medium (2) and long (4) query label sets."""
    return sweep(spark, [(f"{w} labels", carriers.dataset(spark, sf_dir, carrier, w)) for w in (1, 2, 4)], scenario, k=5)


def selectivity_runs(spark: SparkSession, sf_dir: str, carrier: str = "emb_zipf", scenario: str = "overlap") -> DataFrame:
    """Queries near the 75th, 50th, 25th and first percentile of the passing share."""
    d = carriers.dataset(spark, sf_dir, carrier, 1)
    strata = written(selectivity_strata(metrics.selectivity(d.base, d.queries, scenario)), "strata")
    return sweep(spark, [(f"p{p}", carriers.Dataset(d.base, d.queries.join(strata.where(F.col("stratum") == p).select("qid"), "qid"), d.rows)) for p in (75, 50, 25, 1)], scenario)


def topk_runs(spark: SparkSession, sf_dir: str, carrier: str = "doc_attr", scenario: str = "overlap") -> DataFrame:
    """k = 1, 25, 50, 100."""
    d, ks = carriers.dataset(spark, sf_dir, carrier, 1), {f"k={k}": k for k in (1, 25, 50, 100)}
    return sweep(spark, [(s, d) for s in ks], scenario, ("prefilter", "ivfpq", "postfilter", "lattice"), ks)


def size_runs(spark: SparkSession, sf_dir: str, carrier: str = "doc_attr", scenario: str = "containment") -> DataFrame:
    """10, 25, 50 and 100 % of the base."""
    d = carriers.dataset(spark, sf_dir, carrier, 1)
    return sweep(spark, [(f"{p} %", carriers.Dataset(nested_sample(d.base, p), d.queries, d.rows)) for p in (10, 25, 50, 100)], scenario, ("prefilter", "postfilter", "lattice"))


def fixed_runs(spark: SparkSession, sf_dir: str, carrier: str = "doc_fixed4") -> DataFrame:
    """Four positions of three values: every method, equality of all positions."""
    return sweep(spark, [("4x3", carriers.dataset(spark, sf_dir, carrier, 4))], "fixed", METHOD_RUNS, k=3)


# ------------------------------------------------------------------ counters, reports and properties


def search_counters(d: carriers.Dataset, of: str, k: int) -> DataFrame:
    """One row of counters that a search fills while its rows go elsewhere."""
    found, seen = metrics.observed(exact.search(d.base, d.queries, of, k))
    found.write.format("noop").mode("overwrite").save()
    got = seen.get
    return d.base.sparkSession.createDataFrame([(got["found"], got["deepest"], got["farthest"])], "found bigint, deepest int, farthest double")


def reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The runs that events measure, written as CSV and as JSON, and read back."""
    runs, out = tune.event_runs(spark, sf_dir), []
    for form in ("csv", "json"):
        path = f"{shared_dir(spark).rstrip('/')}/vexil-report-{uuid.uuid4().hex}.{form}"
        export_report(runs, path, form)
        out.append(read_report(spark, path, form, "subspace int, config_id string, breadth double, recall double, qps double").withColumn("form", F.lit(form)))
    return out[0].unionByName(out[1])


def event_properties(spark: SparkSession, sf_dir: str) -> DataFrame:
    """k, n, highest: events by the number in their JSON properties; what isn't JSON counts under null."""
    rows = carriers.read(spark, sf_dir, "events").select(F.from_json("props", "k int")["k"].alias("k"), "value")
    return rows.groupBy("k").agg(F.count("*").alias("n"), F.max("value").alias("highest"))
