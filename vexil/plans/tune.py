"""Parameter tuning: sample, measure, interpolate throughput at recall targets, rank, pick, build in full.

One sample serves a whole run, so that sub-boxes of the parameter space compare; ranks are taken once all
of a sub-box is measured. Timed searches run one after the other.
"""

from __future__ import annotations

import itertools
import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import exact, graph
from ..sources import carriers
from ..sources.store import frame_bytes, written
from . import metrics

RUNS = "method string, config_id string, subspace int, scenario string, k int, breadth double, recall double, qps double, build_s double, index_bytes bigint, dist_comps double"


@dataclass(frozen=True)
class Config:
    method: str
    config_id: str
    subspace: int
    params: tuple[tuple[str, float], ...]


def split_space(method: str, values: dict[str, list[float]], cuts: int = 2) -> list[Config]:
    """The grid of values, each dimension cut into `cuts` equal runs; a sub-box is one combination of runs."""
    names = sorted(values)
    out = []
    for picks in itertools.product(*(range(len(values[n])) for n in names)):
        box = 0
        for n, i in zip(names, picks):
            box = box * cuts + i * cuts // len(values[n])
        params = tuple((n, values[n][i]) for n, i in zip(names, picks))
        out.append(Config(method, ",".join(f"{n}={v:g}" for n, v in params), box, params))
    return out


def configs_frame(spark: SparkSession, configs: list[Config]) -> DataFrame:
    return spark.createDataFrame([(c.method, c.config_id, c.subspace, {n: float(v) for n, v in c.params}) for c in configs], "method string, config_id string, subspace int, params map<string,double>")


def sample_base(base: DataFrame, share: float, seed: int = 0) -> DataFrame:
    """Rows by a threshold on the hash of id: the same on every run, and nested for growing shares."""
    return base.where(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1_000_000)) < int(share * 1_000_000))


def measure(configs: list[Config], base: DataFrame, queries: DataFrame, scenarios: list[str], k: int, breadths: list[int], shards: int = 2) -> DataFrame:
    """A row of RUNS for each configuration, scenario and search breadth over base (usually a sample)."""
    spark, rows, n = base.sparkSession, [], queries.count()
    truth = {s: written(exact.search(base, queries, s, k), "truth") for s in scenarios}
    for c in configs:
        start = time.monotonic()
        index = graph.fit(base, c.method, dict(c.params), shards)
        build, size = time.monotonic() - start, frame_bytes(index.nodes)
        for scenario, breadth in itertools.product(scenarios, breadths):
            settings = {"l0": breadth} if c.method == "postfilter" else {"breadth": breadth}
            start = time.monotonic()
            found = written(graph.raw_search(index, queries, scenario, k, **settings), "found")
            near = written(exact.rerank(found.where("id is not null"), base, queries, k), "near")
            qps = n / max(time.monotonic() - start, 1e-9)
            cost = graph.costs(found).agg(F.avg("dist_comps")).first()[0]
            share = metrics.recall(near, truth[scenario], k)
            rows.append((c.method, c.config_id, c.subspace, scenario, k, float(breadth), share, qps, build, size, cost))
    return spark.createDataFrame(rows, RUNS)


def average_over_scenarios(runs: DataFrame) -> DataFrame:
    return runs.groupBy("subspace", "config_id", "breadth").agg(F.avg("recall").alias("recall"), F.avg("qps").alias("qps"))


def qps_at(curve: DataFrame, targets: list[float]) -> DataFrame:
    """subspace, config_id, target, qps by linear interpolation between neighbouring points of a configuration's curve.

    A point on the target gives its own value; a target above the best recall gives null; one below the
    least recall gives the throughput of that least point. Of points with one recall the fastest counts.
    """
    points = curve.groupBy("subspace", "config_id", "recall").agg(F.max("qps").alias("qps"))
    w = Window.partitionBy("subspace", "config_id").orderBy("recall")
    pairs = points.withColumn("r0", F.lag("recall").over(w)).withColumn("q0", F.lag("qps").over(w))
    wanted = F.explode(F.array(*map(F.lit, targets))).alias("target")
    spread = pairs.select("*", wanted)
    straight = F.col("q0") + (F.col("qps") - F.col("q0")) * (F.col("target") - F.col("r0")) / (F.col("recall") - F.col("r0"))
    value = F.when(F.col("recall") == F.col("target"), F.col("qps")).when(F.col("r0").isNull() & (F.col("target") < F.col("recall")), F.col("qps")).when((F.col("r0") < F.col("target")) & (F.col("target") < F.col("recall")), straight)
    return spread.groupBy("subspace", "config_id", "target").agg(F.max(value).alias("qps"))


def rank_configs(at: DataFrame) -> DataFrame:
    """subspace, config_id, total: sum of the ranks by throughput over the targets (missing last)."""
    w = Window.partitionBy("subspace", "target").orderBy(F.desc_nulls_last("qps"))
    return at.withColumn("r", F.rank().over(w)).groupBy("subspace", "config_id").agg(F.sum("r").cast("bigint").alias("total"))


def pick_representatives(ranked: DataFrame) -> DataFrame:
    """subspace, config_id: the best total rank of each sub-box, ties to the smaller config_id."""
    return ranked.groupBy("subspace").agg(F.min(F.struct("total", "config_id"))["config_id"].alias("config_id"))


def tune(method: str, base: DataFrame, queries: DataFrame, values: dict[str, list[float]], scenarios: list[str], k: int = 10, breadths: list[int] | None = None, share: float = 0.3, targets: tuple[float, ...] = (0.8, 0.9, 0.95), cuts: int = 2) -> tuple[DataFrame, DataFrame]:
    """Runs on the sample, and the representatives (subspace, config_id)."""
    configs = split_space(method, values, cuts)
    sample = written(sample_base(base, share), "sample")
    runs = measure(configs, sample, queries, scenarios, k, breadths or [k, 4 * k])
    return runs, pick_representatives(rank_configs(qps_at(average_over_scenarios(runs), list(targets))))


def picked(method: str, picks: DataFrame, values: dict[str, list[float]], cuts: int = 2) -> list[Config]:
    """The picks as settings (as many as sub-boxes)."""
    chosen = {r.config_id for r in picks.collect()}
    return [c for c in split_space(method, values, cuts) if c.config_id in chosen]


def build_full(method: str, picks: DataFrame, values: dict[str, list[float]], base: DataFrame, cuts: int = 2) -> dict[str, graph.GraphIndex]:
    """Indexes on all of base for the representatives only (as many as sub-boxes)."""
    return {c.config_id: graph.fit(base, c.method, dict(c.params)) for c in picked(method, picks, values, cuts)}


def tune_none(method: str) -> Config:
    """Baseline: the defaults, unmeasured."""
    return Config(method, "default", 0, tuple(sorted(graph.DEFAULTS[method].items())))


def tune_exhaustive(method: str, base: DataFrame, queries: DataFrame, values: dict[str, list[float]], scenarios: list[str], k: int = 10, breadths: list[int] | None = None) -> DataFrame:
    """Baseline: every configuration on the full base."""
    return measure(split_space(method, values, 1), base, queries, scenarios, k, breadths or [k, 4 * k])


def reach(find: Callable[[DataFrame, int], DataFrame], base: DataFrame, queries: DataFrame, of: str, k: int, start: int, target: float = 0.93, sample: int = 256) -> int:
    """The first of start, 2 start, 4 start, ... whose search finds `target` of the truths of at most `sample` queries (the first by hash), held against brute force.
    A search as wide as the base finds all, so that the doubling ends there."""
    probes = written(queries.orderBy(F.xxhash64("qid"), "qid").limit(sample), "probes")
    truth, most = written(exact.search(base, probes, of, k), "truth"), base.count()
    while start < most:
        hits, truths = metrics.recall_per_query(find(probes, start), truth, k).agg(F.sum("hits"), F.sum("truths")).first()
        if (hits or 0) >= target * (truths or 0):
            break
        start *= 2
    return start


# Measured points that exercise every rule of interpolation and ranking.
FIXTURE = [
    (1, "a", 10.0, 0.70, 1000.0), (1, "a", 20.0, 0.90, 500.0), (1, "b", 10.0, 0.85, 900.0), (1, "b", 20.0, 0.96, 300.0), (1, "b", 40.0, 0.99, 100.0),
    (2, "c", 10.0, 0.80, 900.0), (2, "c", 20.0, 0.84, 600.0), (2, "d", 10.0, 0.85, 700.0), (2, "d", 20.0, 0.95, 100.0), (2, "e", 10.0, 0.50, 2000.0), (2, "e", 20.0, 0.60, 1500.0),
]


def fixture(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(FIXTURE, "subspace int, config_id string, breadth double, recall double, qps double")


BREADTHS = (10, 20, 40, 80)


def event_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runs as `events` measure them: an event is one search of a configuration (its type, in one of three sub-boxes by user) at one of four breadths.

    Recall is the share of searches whose value lies within twice the breadth; throughput falls with the breadth and the mean value. Events without an id or user measure nothing.
    """
    seen = carriers.read(spark, sf_dir, "events").where("event_id is not null and user_id is not null")
    subspace, breadth = (F.col("user_id") % 3 + 1).cast("int"), F.element_at(F.array(*(F.lit(float(b)) for b in BREADTHS)), (F.col("event_id") % 4 + 1).cast("int"))
    keyed = seen.select(subspace.alias("subspace"), F.concat_ws("-", subspace.cast("string"), "event_type").alias("config_id"), breadth.alias("breadth"), "value")
    sums = keyed.groupBy("subspace", "config_id", "breadth").agg(F.count("*").alias("n"), F.count_if(F.col("value") <= 2 * F.col("breadth")).alias("hits"), F.sum(F.round(F.col("value") * 100).cast("bigint")).alias("cents"))
    cents = F.greatest(F.coalesce("cents", F.lit(0)), F.lit(1))
    return sums.select("subspace", "config_id", "breadth", (F.col("hits") / F.col("n")).alias("recall"), (F.col("n") * 1e6 / (F.col("breadth") * cents)).alias("qps"))


RUNS_SQL = (
    "select subspace, config_id, breadth, hits::double / n::double as recall, n::double * 1e6 / (breadth * greatest(coalesce(cents, 0), 1)::double) as qps from ("
    "select subspace, config_id, breadth, count(*) as n, count(*) filter (where value <= 2 * breadth) as hits, sum(round(value * 100)::bigint)::bigint as cents from ("
    "select (user_id % 3 + 1)::int as subspace, concat_ws('-', (user_id % 3 + 1)::varchar, event_type) as config_id, ([10, 20, 40, 80])[(event_id % 4 + 1)::int]::double as breadth, value "
    "from events where event_id is not null and user_id is not null) group by subspace, config_id, breadth)"
)
INTERPOLATED_SQL = f"""with runs as (select subspace, config_id, recall, max(qps) as qps from ({RUNS_SQL}) group by all), targets as (select unnest([0.8::double, 0.9::double, 0.95::double]) as target),
below as (select config_id, target, max(recall) as lo from runs, targets where recall <= target group by all), above as (select config_id, target, min(recall) as hi from runs, targets where recall >= target group by all),
edges as (select c.config_id, c.subspace, t.target, lo, hi from (select distinct config_id, subspace from runs) c cross join targets t left join below using (config_id, target) left join above using (config_id, target)),
interpolated as (select e.subspace, e.config_id, e.target, case when hi is null then null when lo is null or lo = hi then h.qps else l.qps + (h.qps - l.qps) * (e.target - lo) / (hi - lo) end as qps
from edges e left join runs l on l.config_id = e.config_id and l.recall = lo left join runs h on h.config_id = e.config_id and h.recall = hi)"""
RANKED_SQL = INTERPOLATED_SQL + ", placed as (select *, rank() over (partition by subspace, target order by qps desc nulls last) as r from interpolated), ranked as (select subspace, config_id, sum(r)::bigint as total from placed group by all)"
