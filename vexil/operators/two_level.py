"""Two-level partition for fixed-length equality: coarse clusters, then the commonest labels peeled off one by one.

Within a cluster the most frequent remaining label becomes a sub-cluster of the rows that have it (ties: smaller label), up to
h times; the rest is the last. Rows equal to a query's labels share its first peeled label, so one
sub-cluster per probed cluster is enough.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.distance import l2sq
from ..sources.store import written
from . import ivf
from .exact import small, top_k


@dataclass
class TwoLevelIndex:
    rows: DataFrame  # cluster, sub, id, vec, labels
    peels: DataFrame  # cluster, sub, label
    centroids: DataFrame
    n_clusters: int


def peel(placed: DataFrame, h: int) -> tuple[DataFrame, DataFrame]:
    """placed (list_id, labels, ...) with its sub-cluster, and list_id, sub, label of every peel.

    Only counts are aggregated in a round; the peels are at most h for each cluster.
    """
    spark = placed.sparkSession
    peels = spark.createDataFrame([], "list_id bigint, sub int, label int")
    for sub in range(1, h + 1):
        taken = peels.groupBy("list_id").agg(F.collect_set("label").alias("taken"))
        rest = placed.join(small(taken), "list_id", "left").where(~F.coalesce(F.arrays_overlap("labels", "taken"), F.lit(False)))
        counts = rest.select("list_id", F.explode("labels").alias("label")).groupBy("list_id", "label").count()
        best = counts.groupBy("list_id").agg(F.min(F.struct(-F.col("count"), "label"))["label"].alias("label"))
        peels = written(peels.unionByName(best.select("list_id", F.lit(sub).alias("sub"), "label")), "peels")
    return with_sub(placed, peels, "labels", h), peels


def with_sub(rows: DataFrame, peels: DataFrame, labels: str, h: int) -> DataFrame:
    """The first peel whose label is among the row's; h + 1 for the rest."""
    own = peels.groupBy("list_id").agg(F.array_sort(F.collect_list(F.struct("sub", "label"))).alias("_peels"))
    hit = F.filter("_peels", lambda p: F.array_contains(labels, p["label"]))
    return rows.join(small(own), "list_id", "left").withColumn("sub", F.coalesce(F.try_element_at(hit, F.lit(1))["sub"], F.lit(h + 1))).drop("_peels")


def fit(base: DataFrame, n_clusters: int = 8, h: int = 3, step: int | None = None, seed: int = 0) -> TwoLevelIndex:
    centroids = written(ivf.seed_centroids(base, step) if step else ivf.kmeans_centroids(base, n_clusters, seed=seed), "centroids")
    placed = written(ivf.assign(base.select("id", "vec", "labels"), centroids), "placed")
    rows, peels = peel(placed, h)
    return TwoLevelIndex(written(rows.repartition("list_id", "sub").sortWithinPartitions("list_id", "sub"), "two-level"), peels, centroids, centroids.count())


def visits(index: TwoLevelIndex, queries: DataFrame, probes: int, h: int) -> DataFrame:
    """qid, list_id, sub to scan, with the query's vector and labels."""
    near = ivf.route(queries, index.centroids, probes).join(queries, "qid")
    return with_sub(near, index.peels, "qlabels", h)


def search(index: TwoLevelIndex, queries: DataFrame, k: int, probes: int = 1, h: int = 3) -> DataFrame:
    asked = visits(index, queries, probes, h).select("qid", "qvec", "qlabels", "list_id", "sub")
    hits = index.rows.join(small(asked), ["list_id", "sub"]).where("labels = qlabels")
    return top_k(hits.select("qid", "id", l2sq(F.col("vec"), F.col("qvec")).alias("dist")), k)
