"""Aggregates and table functions for SQL users: medoids and k nearest candidates."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from .distance import l2sq


def _medoid(ids: pd.Series, vecs: pd.Series) -> int | None:
    if not len(ids):
        return None
    x, own = np.stack(vecs.to_numpy()).astype(float), ids.to_numpy()
    far = ((x - x.mean(axis=0)) ** 2).sum(axis=1)
    return int(own[np.lexsort((own, far))[0]])


def medoid_udaf():
    """medoid(id, vec): the id nearest to the group's mean, ties to the smaller. A group has to fit a worker, as lists and
    shards do; `medoids` takes groups of any size. Made on call, since importing needs no session."""
    return F.pandas_udf(_medoid, LongType(), F.PandasUDFType.GROUPED_AGG)


def medoids(base: DataFrame, key: str) -> DataFrame:
    """key, medoid of each group by two aggregations that combine before they shuffle. Null and empty vectors take no part."""
    rows = base.select(key, "id", "vec").where("size(vec) > 0")
    means = rows.select(key, F.posexplode("vec").alias("at", "x")).groupBy(key, "at").agg(F.avg("x").alias("x"))  # groups x dimensions
    centre = means.groupBy(key).agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda s: s["x"]).alias("mean"))
    return rows.join(centre, key).groupBy(key).agg(F.min(F.struct(l2sq(F.col("vec"), F.col("mean")).alias("far"), "id"))["id"].alias("medoid"))


class _Candidates:
    """Keeps the k nearest rows of a partition that hold all asked labels, in a heap of k."""

    def __init__(self) -> None:
        self.best: list[tuple[float, int]] = []

    def eval(self, row, vec, labels, k) -> None:  # noqa: ANN001
        if row["vec"] is None or not set(labels).issubset(row["labels"] or ()):
            return
        far = 0.0
        for x, y in zip(row["vec"], vec):
            far += (x - y) * (x - y)
        item = (-far, -row["id"])
        if len(self.best) < k:
            heapq.heappush(self.best, item)
        elif item > self.best[0]:
            heapq.heapreplace(self.best, item)

    def terminate(self) -> Iterator[tuple[int, float]]:
        for far, own in self.best:
            yield -own, -far


def register_extensions(spark: SparkSession) -> None:
    """medoid(id, vec) and knn_candidates(TABLE(t) PARTITION BY (shard), vec, labels, k) for spark.sql; t has id, vec, labels and shard.
    The function answers per partition, so the caller keeps the k nearest of its rows."""
    spark.udf.register("medoid", medoid_udaf())
    spark.udtf.register("knn_candidates", F.udtf(_Candidates, returnType="id bigint, dist double"))
