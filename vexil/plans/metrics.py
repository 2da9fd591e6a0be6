"""Measures: recall, throughput, selectivity, fronts, normalised costs and reports."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..functions.predicates import Constraint, constraint
from ..operators import exact
from ..sources.store import written


def recall_per_query(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """qid, hits, truths: how many of the true k were found. Queries without truths don't count."""
    hit = truth.where(F.col("rank") <= k).select("qid", "id").join(found.where(F.col("rank") <= k).select("qid", "id", F.lit(1).alias("hit")), ["qid", "id"], "left")
    return hit.groupBy("qid").agg(F.coalesce(F.sum("hit"), F.lit(0)).cast("bigint").alias("hits"), F.count("*").alias("truths"))


def recall(found: DataFrame, truth: DataFrame, k: int) -> float:
    """Mean share of true neighbours found."""
    value = recall_per_query(found, truth, k).agg(F.avg(F.col("hits") / F.col("truths"))).first()[0]
    return 1.0 if value is None else value


def recall_by_stratum(per_query: DataFrame) -> DataFrame:
    stratum = F.when(F.col("truths") < 10, "few").otherwise("full")
    return per_query.groupBy(stratum.alias("stratum")).agg(F.sum("hits").alias("hits"), F.sum("truths").alias("truths"))


def throughput(run: Callable[[], DataFrame], n_queries: int, warm: int = 1, repeats: int = 3) -> tuple[float, float]:
    """Queries per second over the whole batch (median of warm repeats) and its seconds; results go to a sink that drops them."""
    took = []
    for turn in range(warm + repeats):
        start = time.monotonic()
        run().write.format("noop").mode("overwrite").save()
        if turn >= warm:
            took.append(time.monotonic() - start)
    seconds = sorted(took)[len(took) // 2]
    return n_queries / max(seconds, 1e-9), seconds


def observed(found: DataFrame) -> tuple[DataFrame, Observation]:
    """found, and counters of it (rows, deepest rank, largest distance) that any action on it fills without a second pass."""
    seen = Observation()
    counted = found.observe(seen, F.count("*").alias("found"), F.max("rank").alias("deepest"), F.max("dist").alias("farthest"))
    return counted, seen


def selectivity(base: DataFrame, queries: DataFrame, of: str | Constraint) -> DataFrame:
    """qid, passing, total, share of the base that passes. Whether a row passes is up to the two label sets, so that distinct sets meet, not rows;
    combined constraints may ask for other columns and take the rows."""
    want, labels = constraint(of), base.select("id", "labels")
    if want.name == "combined":
        passing = exact.candidates(labels, queries, of).groupBy("qid").agg(F.count("*").alias("passing"))
        counted = queries.select("qid").join(passing, "qid", "left")
    else:
        groups = written(labels.groupBy("labels").agg(F.count("*").alias("rows")), "groups").withColumn("id", F.monotonically_increasing_id())
        asked = written(queries.select(F.col("qlabels").alias("asked")).distinct(), "asked")
        sets = asked.select(F.xxhash64("asked").alias("qid"), F.lit(None).alias("qvec"), F.col("asked").alias("qlabels"))
        hits = exact.candidates(groups, sets, of).groupBy("qlabels").agg(F.sum("rows").alias("passing"))
        counted = queries.select("qid", "qlabels").join(hits, "qlabels", "left")
    total = labels.agg(F.count("*").alias("total"))  # one row
    return counted.join(F.broadcast(total)).select("qid", F.coalesce("passing", F.lit(0)).alias("passing"), "total").withColumn("share", F.col("passing") / F.col("total"))


def invalid_rows(found: DataFrame, base: DataFrame, queries: DataFrame, of: str | Constraint) -> DataFrame:
    """Results that break the constraint; has to be empty."""
    rows = found.join(base.select("id", "labels"), "id", "left").join(queries.select("qid", "qlabels"), "qid")
    return rows.where(~F.coalesce(constraint(of).column(F.col("labels"), F.col("qlabels")), F.lit(False)))


def pareto(runs: DataFrame, by: list[str]) -> DataFrame:
    """Runs that no other run beats in recall and throughput (equal runs stay)."""
    more = F.max("qps").over(Window.partitionBy(*by).orderBy(F.desc("recall")).rowsBetween(Window.unboundedPreceding, -1))
    best = runs.groupBy(*by, "recall").agg(F.max("qps").alias("qps"))
    front = best.withColumn("_more", more).where("_more is null or qps > _more").drop("_more")
    return runs.join(F.broadcast(front), [*by, "recall", "qps"], "left_semi")


def normalised(runs: DataFrame, columns: list[str], by: list[str]) -> DataFrame:
    """Columns scaled to 0..1 within a partition, as `<name>_norm`; 0 where all are equal."""
    w = Window.partitionBy(*by)
    for c in columns:
        low, span = F.min(c).over(w), F.max(c).over(w) - F.min(c).over(w)
        runs = runs.withColumn(f"{c}_norm", F.when(span > 0, (F.col(c) - low) / span).otherwise(F.lit(0.0)))
    return runs


def rollup_report(runs: DataFrame) -> DataFrame:
    return runs.rollup("subspace", "config_id").agg(F.count("*").alias("runs"), F.round(F.max("qps"), 6).alias("best"))


def cube_report(runs: DataFrame) -> DataFrame:
    return runs.cube("subspace", "breadth").agg(F.count("*").alias("runs"), F.round(F.max("recall"), 6).alias("best"))
