"""Inverted lists: coarse centroids, routing, and the post-filtered search over product codes (widened by lists).

`seed` mode takes every step-th row as a centroid and runs no iterations, so that SQL can check
assignments; otherwise centroids come from k-means on a bounded sample.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import block_distances, l2sq, pair_distances, slack
from ..functions.predicates import Constraint, constraint
from ..sources.store import written
from .exact import CELLS, Nearest, QueryBlock, matrix, query_parts, rerank, small, top_k
from .quantize import Codec, add_pooled, code_rows, fit_codec, lloyd, sample_vectors

MAX_LISTS = 65_536
LIST_PARTS = 8  # tasks over which the rows of a list are dealt


def seed_centroids(base: DataFrame, step: int) -> DataFrame:
    """list_id, cvec: the rows whose id is a multiple of step."""
    return base.where(F.col("id") % step == 0).select(F.col("id").alias("list_id"), F.col("vec").alias("cvec"))


def kmeans_centroids(base: DataFrame, lists: int, sample: int = 20_000, rounds: int = 12, seed: int = 0) -> DataFrame:
    c = lloyd(sample_vectors(base, sample), min(lists, MAX_LISTS), rounds, seed)
    return base.sparkSession.createDataFrame([(i, v) for i, v in enumerate(c.tolist())], "list_id bigint, cvec array<double>")


def assign(base: DataFrame, centroids: DataFrame) -> DataFrame:
    """base with list_id of the nearest centroid (ties to the smaller); centroids are bounded and broadcast as arrays."""
    rows = centroids.orderBy("list_id").limit(MAX_LISTS + 1).collect()
    if len(rows) > MAX_LISTS:
        raise ValueError(f"more than {MAX_LISTS} lists")
    ids, c = np.array([r.list_id for r in rows]), np.array([r.cvec for r in rows], float)
    shared = base.sparkSession.sparkContext.broadcast((ids, c))
    columns, kinds = base.columns, dict(base.dtypes)
    at = columns.index("vec")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, centre = shared.value
        ct = np.ascontiguousarray(centre.T)
        for batch in batches:
            out = []
            step = max(1, CELLS // len(centre))
            for lo in range(0, batch.num_rows, step):
                x = matrix(batch.column(at).slice(lo, step))
                rough = block_distances(centre, x)
                # all that may be nearest are compared by exact differences, as equal centroids are common where rows are copied
                row, col = np.nonzero(rough <= (rough.min(axis=1) + 2 * slack(centre, x))[:, None])
                order = np.lexsort((col, pair_distances(ct, np.ascontiguousarray(x.T), col, row), row))
                out.append(names[col[order[np.searchsorted(row, np.arange(len(x)))]]])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.concatenate(out) if out else [], pa.int64())], [*columns, "list_id"])

    return base.mapInArrow(run, ", ".join(f"`{c}` {kinds[c]}" for c in columns) + ", list_id bigint")


def route(queries: DataFrame, centroids: DataFrame, probes: int) -> DataFrame:
    """qid, list_id, ord: each query's nearest lists, from 1. Centroids are bounded (MAX_LISTS)."""
    near = queries.select("qid", "qvec").join(F.broadcast(centroids)).select("qid", "list_id", l2sq(F.col("cvec"), F.col("qvec")).alias("d"))
    return near.withColumn("ord", F.row_number().over(Window.partitionBy("qid").orderBy("d", "list_id"))).where(F.col("ord") <= probes).select("qid", "list_id", "ord")


@dataclass
class IvfIndex:
    base: DataFrame
    lists: DataFrame  # list_id, id, labels, code, vec
    centroids: DataFrame
    codec: Codec
    n_lists: int


def fit(base: DataFrame, n_lists: int = 16, m: int = 8, bits: int = 4, seed: int = 0, step: int | None = None, sample: int = 20_000) -> IvfIndex:
    """The codes leave labels out of the build; labels ride along for the check after the search."""
    centroids = written(seed_centroids(base, step) if step else kmeans_centroids(base, n_lists, sample, seed=seed), "centroids")
    codec = fit_codec(sample_vectors(base, sample), "pq", m, bits, seed)
    coded = code_rows(assign(base.select("id", "vec", "labels"), centroids), codec, ["id", "labels", "list_id", "vec"])
    dealt = coded.repartition("list_id", F.pmod(F.xxhash64("id"), F.lit(LIST_PARTS)))
    return IvfIndex(base, written(dealt.sortWithinPartitions("list_id", "id"), "ivf"), centroids, codec, centroids.count())


def scan_lists(index: IvfIndex, visits: DataFrame, queries: DataFrame, scenario: str, k: int, pool: int) -> DataFrame:
    """qid, id, dist over the visited lists (qid, list_id): of the rows of a list in an Arrow batch, the pool best passing ones by code distance
    are scored exactly where they lie; a task returns the k nearest of these, and as many as pass if they are fewer."""
    block, met = QueryBlock(queries), visits.join(queries.select("qid"), "qid", "left_semi").select("list_id", "qid").toArrow()
    lists, at = met.column(0).to_numpy(), np.searchsorted(block.qid, met.column(1).to_numpy())
    order = np.argsort(lists, kind="stable")
    names, first = np.unique(lists[order], return_index=True)
    visitors = dict(zip(names.tolist(), np.split(at[order], first[1:])))
    shared = index.base.sparkSession.sparkContext.broadcast((index.codec, block, visitors))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec, block, visitors = shared.value
        best = Nearest(len(block.qid), k)
        for batch in batches:
            own_list = batch.column(4).to_numpy(zero_copy_only=False)
            for name in np.unique(own_list).tolist():
                if name in visitors:
                    part = batch.take(pa.array(np.flatnonzero(own_list == name)))
                    visits = np.zeros(len(block.qid), bool)
                    visits[visitors[name]] = True
                    passing = ((own[visits[own]], rows) for own, rows in block.passing(part.column(1), scenario) if visits[own].any())
                    add_pooled(best, block, codec, part, passing, k, pool)
        yield from best.rows(block.qid)

    return index.lists.select("id", "labels", "code", "vec", "list_id").mapInArrow(run, "qid bigint, id bigint, dist double")


def probe(index: IvfIndex, visits: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, id, labels, approx over the visited lists (qid, list_id), as a join: for combined predicates, which only Spark evaluates."""
    shared = index.base.sparkSession.sparkContext.broadcast(index.codec)
    joined = index.lists.join(small(visits.join(queries.select("qid", "qvec"), "qid")), "list_id").select("qid", "id", "labels", "code", "qvec")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = shared.value
        for batch in batches:
            n = batch.num_rows
            if n:
                codes = np.frombuffer(b"".join(batch.column(3).to_pylist()), np.uint8).reshape(n, -1)
                q = batch.column(4).flatten().to_numpy(zero_copy_only=False).reshape(n, -1)
                gap = ((codec.decode(codes) - codec.turn(q)) ** 2).sum(axis=1)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(gap)], ["qid", "id", "labels", "approx"])

    return joined.mapInArrow(run, "qid bigint, id bigint, labels array<int>, approx double")


def search(index: IvfIndex, queries: DataFrame, of: str | Constraint, k: int, probes: int = 1, growth: int = 2, most: int | None = None, pool: int | None = None) -> DataFrame:
    """Probe, check labels, widen for the queries that still lack k, rerank. Rounds only visit the new lists.

    Valid rows of all rounds are merged, because lists aren't visited in order of distance. The pool (default 4 k, k at least) is kept of the
    rows of each list in a batch; for combined predicates, of all valid rows.
    """
    want, most = constraint(of), min(index.n_lists, most or index.n_lists)
    order = written(route(queries, index.centroids, most), "route")
    open_queries, done, scope, parts = queries.select("qid"), 0, min(probes, most), []
    while True:
        visits = order.where((F.col("ord") > done) & (F.col("ord") <= scope)).join(open_queries, "qid", "left_semi")
        if want.name == "combined":
            found = probe(index, visits, queries).join(small(queries.select("qid", "qlabels")), "qid").where(want.column(F.col("labels"), F.col("qlabels"))).select("qid", "id", "approx")
        else:
            left = queries.join(open_queries, "qid", "left_semi")
            found = reduce(DataFrame.unionByName, (scan_lists(index, visits, part, want.name, k, max(k, pool or 4 * k)) for part in query_parts(left, k + scope)))
        parts.append(written(found, "round"))
        merged = parts[0]
        for p in parts[1:]:
            merged = merged.unionByName(p)
        if scope >= most:
            break
        full = merged.groupBy("qid").count().where(F.col("count") >= k)
        open_queries = written(queries.select("qid").join(full, "qid", "left_anti"), "open")
        if not open_queries.limit(1).count():
            break
        done, scope = scope, min(most, scope * growth)
    if want.name != "combined":
        return top_k(merged, k)
    best = merged.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy("approx", "id"))).where(F.col("r") <= (pool or 4 * k))
    return rerank(best, index.base, queries, k)


def rounds_needed(index: IvfIndex, queries: DataFrame, of: str | Constraint, k: int, probes: int = 1, growth: int = 2) -> DataFrame:
    """qid, rounds, scope: how often each query widens until k valid rows are in scope (all lists at most)."""
    want = constraint(of)
    order = route(queries, index.centroids, index.n_lists)
    valid = index.lists.select("list_id", "labels").join(small(queries.select("qid", "qlabels")), want.column(F.col("labels"), F.col("qlabels"))).groupBy("qid", "list_id").count()
    run = Window.partitionBy("qid").orderBy("ord").rowsBetween(Window.unboundedPreceding, 0)
    reach = order.join(valid, ["qid", "list_id"], "left").withColumn("have", F.sum(F.coalesce("count", F.lit(0))).over(run))
    first = reach.groupBy("qid").agg(F.coalesce(F.min(F.when(F.col("have") >= k, F.col("ord"))), F.lit(index.n_lists)).alias("need"))
    steps = F.lit(1)
    scope, edge = F.lit(probes), probes
    while edge < index.n_lists:
        steps, scope = steps + (F.col("need") > edge).cast("int"), F.when(F.col("need") > edge, F.lit(min(index.n_lists, edge * growth))).otherwise(scope)
        edge *= growth
    return first.select("qid", steps.alias("rounds"), scope.cast("int").alias("scope"))
