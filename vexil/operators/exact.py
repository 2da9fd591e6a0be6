"""Pre-filtered exact search: filter first, full-precision distance on the survivors, top-k.

Routes (same rows, different plans): `column` evaluates the predicate beside broadcast queries,
`group` joins equal label sets by hash, `posting` probes the rarest asked label (containment) or every
asked label (overlap), `bitmap` joins filter maps on the bucket, and `block` scores Arrow batches by one
matrix product, scores what may be among the k nearest exactly, and keeps k rows per task and query: the route for large data.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import METRICS, block_distances, pair_distances, slack
from ..functions.predicates import Constraint, constraint
from ..sources.store import written
from . import bitmaps

MAX_QUERY_BYTES = 64_000_000
CELLS = 1 << 20  # entries of one matrix of queries and rows


def top_k(scored: DataFrame, k: int) -> DataFrame:
    """qid, rank, id, dist: the k nearest of each query by (dist, id). Plans as a group limit before and after the shuffle."""
    order = Window.partitionBy("qid").orderBy("dist", "id")
    return scored.select("qid", "id", "dist").withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("qid", "rank", "id", "dist")


def small(queries: DataFrame, rows: int | None = None) -> DataFrame:
    """Broadcast hint for queries after a check of their size; without it beyond the bound."""
    sample = queries.limit(1).collect()
    if not sample:
        return F.broadcast(queries)
    each = 8 * sum(len(v) if isinstance(v, list) else 2 for v in sample[0])
    most = MAX_QUERY_BYTES // each
    return F.broadcast(queries) if queries.limit(most + 1).count() <= most else queries


def candidates(base: DataFrame, queries: DataFrame, of: str | Constraint, route: str = "auto") -> DataFrame:
    """qid, qvec with the columns of the base rows that pass."""
    want = constraint(of)
    name = want.name
    if route == "auto":
        route = {"equality": "group", "fixed": "group", "containment": "posting", "overlap": "posting"}.get(name, "column")
    if route == "column":
        return base.join(small(queries), want.column(F.col("labels"), F.col("qlabels")))
    if route == "group":
        return base.join(queries, base.labels == queries.qlabels)
    if route == "bitmap":
        rows = bitmaps.with_ordinals(base)
        maps = bitmaps.filter_map(name, bitmaps.build_label_bitmaps(rows), queries, rows)
        return bitmaps.bitmap_members(maps, rows).join(small(queries.select("qid", "qvec", "qlabels")), "qid")
    if route == "posting":
        flat = base.withColumn("label", F.explode("labels"))
        if name == "overlap":
            asked = queries.withColumn("label", F.explode("qlabels"))
            # a row stands under each common label; it counts under the smallest
            return flat.join(small(asked), "label").where(F.array_min(F.array_intersect("labels", "qlabels")) == F.col("label"))
        if name == "containment":
            counts = flat.groupBy("label").count()
            asked = queries.select("qid", F.explode("qlabels").alias("label")).join(counts, "label", "left")
            rarest = asked.groupBy("qid").agg(F.min(F.struct(F.coalesce("count", F.lit(0)), "label"))["label"].alias("label"))
            probes = queries.join(rarest, "qid")
            hits = flat.join(small(probes), "label").where(want.column(F.col("labels"), F.col("qlabels")))
            everything = queries.where("size(qlabels) = 0")
            return hits.unionByName(base.join(F.broadcast(everything)).withColumn("label", F.lit(None).cast("int")))
    raise ValueError(f"no {route} route for {name}")


def search(base: DataFrame, queries: DataFrame, of: str | Constraint, k: int, route: str = "auto", metric: str = "l2") -> DataFrame:
    if route == "block" or route == "auto" and constraint(of).name != "combined":
        return block_search(base, queries, of, k, metric)
    passing = candidates(base, queries, of, route)
    return top_k(passing.select("qid", "id", METRICS[metric](F.col("vec"), F.col("qvec")).alias("dist")), k)


def rerank(found: DataFrame, base: DataFrame, queries: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """Exact distances of found (qid, id), and the k nearest. Vectors are fetched for candidates only."""
    pairs = found.select("qid", "id").distinct().join(queries.select("qid", "qvec"), "qid")
    scored = pairs.join(base.select("id", "vec"), "id").select("qid", "id", METRICS[metric](F.col("vec"), F.col("qvec")).alias("dist"))
    return top_k(scored, k)


def label_masks(rows: np.ndarray, asked: np.ndarray, scenario: str) -> np.ndarray:
    """Queries x rows of True where the row passes; both sides as 0/1 label matrices."""
    if scenario == "nofilter":
        return np.ones((len(asked), len(rows)), bool)
    common, size = asked @ rows.T, asked.sum(axis=1)[:, None]
    if scenario == "containment":
        return common >= size
    if scenario == "overlap":
        return common > 0
    return (common >= size) & (rows.sum(axis=1)[None, :] == size)


class QueryBlock:
    """Queries as arrays, small enough to broadcast (checked)."""

    def __init__(self, queries: DataFrame):
        most = MAX_QUERY_BYTES // 8
        rows = queries.select("qid", "qvec", "qlabels").orderBy("qid").limit(most // 3 + 1).collect()
        if sum(len(r.qvec) + len(r.qlabels) + 2 for r in rows) > most:
            raise ValueError("the queries exceed the broadcast bound: search them in blocks")
        self.qid = np.array([r.qid for r in rows], np.int64)
        self.q = np.array([r.qvec for r in rows], float) if rows else np.zeros((0, 1))
        self.labels = sorted({x for r in rows for x in r.qlabels})
        at = {x: i for i, x in enumerate(self.labels)}
        self.asked = np.zeros((len(rows), len(self.labels)), np.float32)
        for i, r in enumerate(rows):
            self.asked[i, [at[x] for x in r.qlabels]] = 1

    def sets(self) -> list[tuple[np.ndarray, np.ndarray]]:
        """Each distinct set of asked labels as 0/1 positions, and the queries that ask for it."""
        if not hasattr(self, "_sets"):
            own: dict[bytes, list[int]] = {}
            for i, key in enumerate(np.packbits(self.asked > 0, axis=1)):
                own.setdefault(key.tobytes(), []).append(i)
            self._sets = [(self.asked[at[0]], np.array(at)) for at in own.values()]
        return self._sets

    def one_hot(self, labels: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
        """0/1 matrix over the asked labels, and each row's number of labels."""
        size = labels.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
        out = np.zeros((len(labels), len(self.labels)), np.float32)
        if self.labels:
            own, known = labels.flatten().to_numpy(zero_copy_only=False), np.array(self.labels)
            at = np.minimum(np.searchsorted(known, own), len(known) - 1)
            hit = known[at] == own
            out[np.repeat(np.arange(len(labels)), size)[hit], at[hit]] = 1
        return out, size

    def passing(self, labels: pa.ListArray, scenario: str) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Queries with one set of asked labels, and the rows that pass for them; neither is empty."""
        if scenario == "nofilter":
            if len(labels) and len(self.qid):
                yield np.arange(len(self.qid)), np.arange(len(labels))
            return
        hot, size = self.one_hot(labels)
        if scenario in ("equality", "fixed"):
            # rows of one set meet the queries of the same set; a row with a label that nobody asks for meets none
            known = np.flatnonzero(hot.sum(axis=1) == size)
            at: dict[bytes, list[int]] = {}
            for i, key in zip(known.tolist(), np.packbits(hot[known] > 0, axis=1)):
                at.setdefault(key.tobytes(), []).append(i)
            for kind, own in self.sets():
                rows = at.get(np.packbits(kind > 0).tobytes())
                if rows:
                    yield own, np.array(rows)
            return
        step = max(1, CELLS // max(1, len(labels)))
        for lo in range(0, len(self.sets()), step):
            some = self.sets()[lo : lo + step]
            for (_, own), mask in zip(some, label_masks(hot, np.stack([kind for kind, _ in some]), scenario)):
                rows = np.flatnonzero(mask)
                if len(rows):
                    yield own, rows


class Nearest:
    """The k nearest rows of each query so far, by (dist, id)."""

    def __init__(self, queries: int, k: int):
        self.dist, self.id = np.full((queries, k), np.inf), np.full((queries, k), np.iinfo(np.int64).max)

    def bound(self, own: np.ndarray) -> np.ndarray:
        return self.dist[own, -1]

    def add(self, row: np.ndarray, ids: np.ndarray, dist: np.ndarray) -> None:
        k = self.dist.shape[1]
        for lo in range(0, k and len(row), CELLS):
            part, pid, pd = row[lo : lo + CELLS], ids[lo : lo + CELLS], dist[lo : lo + CELLS]
            own = np.unique(part)
            row_, id_, dist_ = np.concatenate([part, np.repeat(own, k)]), np.concatenate([pid, self.id[own].ravel()]), np.concatenate([pd, self.dist[own].ravel()])
            order = np.lexsort((id_, dist_, row_))
            first = np.searchsorted(row_[order], own)
            keep = order[(first[:, None] + np.arange(k)).ravel()]  # each query has k entries at least
            self.id[own], self.dist[own] = id_[keep].reshape(-1, k), dist_[keep].reshape(-1, k)

    def rows(self, qid: np.ndarray) -> Iterator[pa.RecordBatch]:
        for lo in range(0, len(qid), 10_000):
            row, col = np.nonzero(np.isfinite(self.dist[lo : lo + 10_000]))
            yield pa.RecordBatch.from_arrays([pa.array(qid[lo + row]), pa.array(self.id[lo + row, col]), pa.array(self.dist[lo + row, col])], ["qid", "id", "dist"])


def matrix(vectors: pa.ListArray) -> np.ndarray:
    return vectors.flatten().to_numpy(zero_copy_only=False).astype(float, copy=False).reshape(len(vectors), -1)


def least(dist: np.ndarray, n: int) -> np.ndarray:
    """The n-th smallest of each line, or infinity if a line is shorter."""
    return np.partition(dist, n - 1, axis=1)[:, n - 1] if n <= dist.shape[1] else np.full(len(dist), np.inf)


def query_parts(queries: DataFrame, k: int) -> list[DataFrame]:
    """Queries in blocks which, with k answers each, take about half the broadcast bound."""
    size = queries.agg(F.sum(F.size("qvec") + F.size("qlabels") + 2 + 2 * k)).first()[0] or 0
    parts = -(-2 * size * 8 // MAX_QUERY_BYTES)
    return [queries.where(F.pmod(F.xxhash64("qid"), F.lit(parts)) == i) for i in range(parts)] if parts > 1 else [queries]


def block_search(base: DataFrame, queries: DataFrame, of: str | Constraint, k: int, metric: str = "l2") -> DataFrame:
    """Each task returns the k nearest of its rows for every query, exact in distances and ties; these are merged."""
    scenario = constraint(of).name
    if scenario == "combined":
        raise ValueError("combined predicates take the column or bitmap route")
    found = [_block_scan(base, part, scenario, k, metric) for part in query_parts(queries, k)]
    return top_k(reduce(DataFrame.unionByName, found), k)


def nearest(block: QueryBlock, batches: Iterator[pa.RecordBatch], scenario: str, k: int, metric: str = "l2") -> Iterator[pa.RecordBatch]:
    """qid, id, dist: the k nearest passing rows of the batches (id, vec, labels) for each query. No matrix has more than CELLS entries, or a batch's rows for one query."""
    best, qt = Nearest(len(block.qid), k), np.ascontiguousarray(block.q.T)
    for batch in batches:
        if not batch.num_rows or not len(block.qid):
            continue
        ids, x = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64), matrix(batch.column(1))
        xt = np.ascontiguousarray(x.T)
        for own, rows in block.passing(batch.column(2), scenario):
            near, step = x[rows], max(1, CELLS // len(rows))
            for lo in range(0, len(own), step):
                some = own[lo : lo + step]
                dist = block_distances(near, block.q[some], metric)
                edge, off = best.bound(some), 2 * slack(near, block.q[some], metric)
                hit = dist <= (edge + off)[:, None]
                many = np.flatnonzero(hit.sum(axis=1) > 4 * k)  # where the bound is loose yet, this batch's own k-th may be closer
                if len(many):
                    hit[many] = dist[many] <= (np.minimum(edge[many], least(dist[many], k)) + off[many])[:, None]
                row, col = np.nonzero(hit)
                best.add(some[row], ids[rows[col]], pair_distances(xt, qt, rows[col], some[row], metric))
    yield from best.rows(block.qid)


def _block_scan(base: DataFrame, queries: DataFrame, scenario: str, k: int, metric: str) -> DataFrame:
    shared = base.sparkSession.sparkContext.broadcast(QueryBlock(queries))
    rows = base.where("vec is not null").select("id", "vec", "labels")
    return rows.mapInArrow(lambda batches: nearest(shared.value, batches, scenario, k, metric), "qid bigint, id bigint, dist double")


def positions(base: DataFrame, queries: DataFrame, marks: DataFrame) -> DataFrame:
    """qid, pos: how many rows of the base, passing or not, come no later than a query's mark (qid, id, dist) in order of (dist, id). Only counts leave a task."""
    asked = queries.join(marks.select("qid", "id", "dist"), "qid")
    counted = [_positions(base, part) for part in query_parts(asked, 1)]
    return reduce(DataFrame.unionByName, counted).groupBy("qid").agg(F.sum("n").alias("pos"))


def _positions(base: DataFrame, asked: DataFrame) -> DataFrame:
    asked = written(asked, "marks")
    block, at = QueryBlock(asked), {r.qid: (r.dist, r.id) for r in asked.select("qid", "dist", "id").collect()}  # as many as the block's queries
    edge, last = np.array([at[q][0] for q in block.qid.tolist()], float), np.array([at[q][1] for q in block.qid.tolist()], np.int64)
    shared = base.sparkSession.sparkContext.broadcast((block, edge, last))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, edge, last = shared.value
        n, qt = np.zeros(len(edge), np.int64), np.ascontiguousarray(block.q.T)
        for batch in batches:
            if not batch.num_rows or not len(edge):
                continue
            ids, x = batch.column(0).to_numpy(zero_copy_only=False), matrix(batch.column(1))
            xt, step = np.ascontiguousarray(x.T), max(1, CELLS // len(x))
            for lo in range(0, len(edge), step):
                some = np.arange(lo, min(lo + step, len(edge)))
                gap, off = block_distances(x, block.q[some]) - edge[some, None], 2 * slack(x, block.q[some])[:, None]
                n[some] += (gap < -off).sum(axis=1)
                row, col = np.nonzero(np.abs(gap) <= off)
                dist, row = pair_distances(xt, qt, col, some[row]), some[row]
                n += np.bincount(row[(dist < edge[row]) | (dist == edge[row]) & (ids[col] <= last[row])], minlength=len(n))
        yield pa.RecordBatch.from_arrays([pa.array(block.qid), pa.array(n)], ["qid", "n"])

    return base.where("vec is not null").select("id", "vec").mapInArrow(run, "qid bigint, n bigint")
