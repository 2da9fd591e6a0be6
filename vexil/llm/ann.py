"""Operator 6: approximate nearest neighbours with an adaptive dimension scan.

Vectors are rotated by a fixed random orthogonal matrix and dealt to inverted lists (k-means
fitted on a bounded sample; every vector is indexed). A query probes its nearest lists, in two waves: first as
few as hold 8 k others, then the rest, with the k-th best distance of the first wave as a bound. Within
a list the rotated vectors lie in column blocks. The k candidates that are nearest in the first block are scored
at once; after each block a hypothesis test compares the others' partial distance, scaled to all dimensions, with the
k-th best so far, and abandons the candidates that would lie beyond it with high confidence. Survivors are
scored exactly on the original vectors in double precision. `scan_counts` tells how many were abandoned.

The test: after a random rotation the share of a squared distance that lies in m of d columns follows
Beta(m / 2, (d - m) / 2). A candidate goes if its partial distance would be larger than this, with probability
1 - alpha, for any vector within the bound.

The number of probed lists is set by measuring recall on a bounded sample of queries against
brute force over all rows; a query whose lists hold too few vectors goes on to further ones until
k others are covered, and empty lists don't count. Lists are cut into blocks of bounded size, so a list with most of
the rows is shared by many tasks; each block returns at most k rows for a query.

Cases: vectors that are null, zero, of another length than most, or that hold null or non-finite
components take no part. Rows that share a vec_id are one vector (the smallest by components). Ties
go to the smaller vec_id; with at most k candidates all are returned, else k.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

BLOCK_ROWS = 8_192
CHUNK = 1_024
ALPHA = 0.001


@dataclass
class Index:
    vectors: DataFrame  # vec_id, v (original doubles), list, sub
    rotation: np.ndarray
    centroids: np.ndarray  # in rotated space
    subs: DataFrame  # list, subs
    sizes: np.ndarray  # rows of each list
    n: int


def usable(vectors: DataFrame, vec_id: str, column: str) -> DataFrame:
    """vec_id, v: the vectors that take part, one for each id."""
    v = F.col(column).cast("array<double>")
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    kept = vectors.select(F.col(vec_id).cast("bigint").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & fine)
    kept = kept.groupBy("vec_id").agg(F.min("v").alias("v"))
    sizes = kept.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    return kept.where(F.size("v") == (sizes.d if sizes else 0))


def _matrix(column: pa.Array, d: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, d)


def _nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return (c * c).sum(axis=1) - 2 * (x @ c.T)


def _kmeans(x: np.ndarray, k: int, rounds: int, seed: int) -> np.ndarray:
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)]
    for _ in range(rounds):
        at = np.argmin(_nearest(x, c), axis=1)
        sums, n = np.zeros_like(c), np.bincount(at, minlength=len(c))
        np.add.at(sums, at, x)
        c = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], c)
    return c


def fit(vectors: DataFrame, vec_id: str = "vec_id", column: str = "embedding", lists: int | None = None, sample: int = 20_000, seed: int = 9) -> Index:
    """lists defaults to about the square root of the rows, at most 16,384; sample rows (by hash) fit the centroids."""
    base = materialise(usable(vectors, vec_id, column), "vectors")
    n = base.count()
    d = len(base.first().v) if n else 1
    lists = lists or max(1, min(16_384, int(n**0.5) // 2))
    rotation = np.linalg.qr(np.random.default_rng(seed).normal(size=(d, d)))[0]
    # at most 2 * sample rows of d doubles, picked by hash
    share = int(min(1.0, sample / max(1, n)) * (1 << 30))
    seen = base.where(F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(1 << 30)) <= share).orderBy("vec_id").limit(2 * sample).collect()
    x = np.array([r.v for r in seen]) @ rotation if seen else np.zeros((1, d))
    centroids = _kmeans(x, lists, 8, seed)
    shared = base.sparkSession.sparkContext.broadcast((rotation, centroids))  # lists * d doubles, lists <= 16,384

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turn, c = shared.value
        for batch in batches:
            at = [np.argmin(_nearest(_matrix(batch.column(1).slice(lo, CHUNK), d) @ turn, c), axis=1) for lo in range(0, batch.num_rows, CHUNK)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.concatenate(at) if at else [], pa.int32())], ["vec_id", "v", "list"])

    placed = base.mapInArrow(run, "vec_id bigint, v array<double>, list int")
    placed = materialise(placed, "lists")
    counts = placed.groupBy("list").count()
    sizes = np.zeros(len(centroids), np.int64)
    for r in counts.collect():  # at most a row for each list
        sizes[r["list"]] = r["count"]
    subs = counts.select("list", F.ceil(F.col("count") / BLOCK_ROWS).cast("int").alias("subs"))
    indexed = placed.join(F.broadcast(subs), "list").withColumn("sub", F.pmod(F.xxhash64("vec_id"), "subs").cast("int")).drop("subs")
    return Index(indexed, rotation, centroids, subs, sizes, n)


def _order(parts: tuple[np.ndarray, np.ndarray, np.ndarray], q: np.ndarray) -> np.ndarray:
    """Lists that hold vectors, nearest first, for each query."""
    turn, c, sizes = parts
    filled = np.flatnonzero(sizes)
    return filled[np.argsort(_nearest(q @ turn, c[filled]), axis=1, kind="stable")]


@lru_cache(64)
def share_limits(d: int, block: int, alpha: float) -> tuple[float, ...]:
    """After each column block, the share of a squared distance that is exceeded with probability alpha."""
    t = np.linspace(0, 1, 20_001)[1:-1]
    out = []
    for m in range(block, d, block):
        log = (m / 2 - 1) * np.log(t) + ((d - m) / 2 - 1) * np.log1p(-t)
        mass = np.cumsum(np.exp(log - log.max()))
        out.append(float(t[min(len(t) - 1, np.searchsorted(mass, (1 - alpha) * mass[-1]))]) if alpha else np.inf)
    return (*out, 1 + 1e-9)


def scan_block(ids: np.ndarray, x: np.ndarray, rotated: np.ndarray, qid: np.ndarray, q: np.ndarray, q_rotated: np.ndarray, bounds: np.ndarray, k: int, block: int = 16, alpha: float = ALPHA) -> Iterator[tuple[np.ndarray, np.ndarray, int, int]]:
    """For each query: ids and exact distances of its k best of one block of vectors within its bound, the
    candidates, and how many of them were abandoned before their last dimension."""
    d = x.shape[1]
    for j in range(len(qid)):
        alive = np.flatnonzero(ids != qid[j])
        seen, dropped, done = len(alive), 0, min(d, block)
        rounding = 1e-12 * float(q[j] @ q[j])  # of the rotation, where the bound is about 0
        part = ((rotated[alive, :done] - q_rotated[j, :done]) ** 2).sum(axis=1)
        near = np.argpartition(part, k - 1)[:k] if seen > k else np.arange(seen)
        chosen = [alive[near]]
        exact = [np.sqrt(((x[chosen[0]] - q[j]) ** 2).sum(axis=1))]
        bound = min(bounds[j], np.sort(exact[0])[k - 1]) if seen >= k else bounds[j]
        alive, part = np.delete(alive, near), np.delete(part, near)
        for limit in share_limits(d, block, alpha):
            keep = part <= (bound**2 * limit + rounding if limit < np.inf else np.inf)
            dropped += 0 if done == d else int(len(keep) - keep.sum())
            alive, part = alive[keep], part[keep]
            if done == d or not len(alive):
                break
            step = slice(done, min(d, done + block))
            part = part + ((rotated[alive, step] - q_rotated[j, step]) ** 2).sum(axis=1)
            done = min(d, done + block)
        chosen.append(alive)
        exact.append(np.sqrt(((x[alive] - q[j]) ** 2).sum(axis=1)))
        found, score = ids[np.concatenate(chosen)], np.concatenate(exact)
        order = np.lexsort((found, score))[:k]
        order = order[score[order] <= bounds[j]]
        yield found[order], score[order], seen, dropped


def _scan(index: Index, visits: DataFrame, k: int, alpha: float) -> DataFrame:
    """query_id, vec_id, score, seen, dropped for visits (list, query_id, q, bound); one row without vec_id for each query and block carries the counts."""
    turn = index.vectors.sparkSession.sparkContext.broadcast(index.rotation)
    placed = visits.join(F.broadcast(index.subs), "list").select("list", F.explode(F.sequence(F.lit(0), F.col("subs") - 1)).alias("sub"), "query_id", "q", "bound")

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(left) and len(right):
            left = left.sort_values("vec_id")
            ids, x, q = left["vec_id"].to_numpy(), np.stack(left["v"].to_numpy()), np.stack(right["q"].to_numpy())
            parts = scan_block(ids, x, x @ turn.value, right["query_id"].to_numpy(), q, q @ turn.value, right["bound"].to_numpy(), k, alpha=alpha)
            for own, (i, score, seen, dropped) in zip(right["query_id"], parts):
                out.append(pd.DataFrame({"query_id": own, "vec_id": pd.array([None, *i], "Int64"), "score": [0.0, *score], "seen": [seen] + [0] * len(i), "dropped": [dropped] + [0] * len(i)}))
        empty = pd.DataFrame({"query_id": np.zeros(0, np.int64), "vec_id": pd.array([], "Int64"), "score": np.zeros(0), "seen": np.zeros(0, np.int64), "dropped": np.zeros(0, np.int64)})
        return pd.concat(out, ignore_index=True) if out else empty

    return index.vectors.groupBy("list", "sub").cogroup(placed.groupBy("list", "sub")).applyInPandas(run, "query_id bigint, vec_id bigint, score double, seen bigint, dropped bigint")


def _waves(index: Index, queries: DataFrame, k: int, probes: int | None, alpha: float) -> DataFrame:
    """Rows of _scan over both waves."""
    d, spark = len(index.rotation), queries.sparkSession
    probes = min(len(index.centroids), probes or len(index.centroids))
    shared = spark.sparkContext.broadcast((index.rotation, index.centroids, index.sizes))

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sizes = shared.value[2]
        for batch in batches:
            for lo in range(0, batch.num_rows, CHUNK):
                part = batch.slice(lo, CHUNK)
                order = _order(shared.value, _matrix(part.column(1), d))
                lead = (np.cumsum(sizes[order], axis=1) <= k).sum(axis=1) + 1  # k others and the query itself
                near = [own[: max(probes, n)] for own, n in zip(order.astype(np.int32), lead)]
                lead = np.minimum([len(own) for own in near], (np.cumsum(sizes[order], axis=1) <= 8 * k).sum(axis=1) + 1)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(near, pa.list_(pa.int32())), pa.array(lead, pa.int32())], ["query_id", "q", "lists", "lead"])

    routed = materialise(queries.select("vec_id", "v").mapInArrow(route, "query_id bigint, q array<double>, lists array<int>, lead int"), "routed")
    nowhere = F.lit(float("inf"))
    first = routed.select("query_id", "q", F.explode(F.slice("lists", F.lit(1), F.col("lead"))).alias("list"), nowhere.alias("bound"))
    near = materialise(_scan(index, first, k, alpha), "wave")
    rank = Window.partitionBy("query_id").orderBy("score", "vec_id")
    kth = near.where("vec_id is not null").withColumn("r", F.row_number().over(rank)).where(F.col("r") == k).select("query_id", F.col("score").alias("bound"))
    rest = routed.where("size(lists) > lead").select("query_id", "q", F.explode(F.slice("lists", F.col("lead") + 1, F.size("lists"))).alias("list"))
    rest = rest.join(kth, "query_id", "left").withColumn("bound", F.coalesce("bound", nowhere))
    return near.unionByName(_scan(index, rest, k, alpha))


def search(index: Index, queries: DataFrame, k: int = 10, probes: int | None = None, alpha: float = ALPHA) -> DataFrame:
    """query_id, rank, vec_id, score for queries (vec_id, v). A query probes more lists where the nearest `probes` hold fewer than k + 1 vectors."""
    near = _waves(index, queries, k, probes, alpha).where("vec_id is not null")
    rank = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return near.withColumn("rank", F.row_number().over(rank)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def scan_counts(index: Index, queries: DataFrame, k: int = 10, probes: int | None = None, alpha: float = ALPHA) -> DataFrame:
    """query_id, candidates, abandoned: candidates in the probed lists, and those given up before their last dimension."""
    return _waves(index, queries, k, probes, alpha).groupBy("query_id").agg(F.sum("seen").alias("candidates"), F.sum("dropped").alias("abandoned"))


def exact(index: Index, queries: DataFrame, k: int = 10) -> DataFrame:
    """Brute force over all lists without abandoning: the measure of recall."""
    return search(index, queries, k, None, 0.0)


def calibrate(index: Index, queries: DataFrame, k: int = 10, target: float = 0.95, sample: int = 48) -> int:
    """Lists to probe so that at least target of the true neighbours of a bounded sample of queries lie in them."""
    picked = materialise(queries.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample), "sample")
    truth = exact(index, picked, k).join(index.vectors.select("vec_id", "list"), "vec_id").select("query_id", "list").collect()
    order = {}
    for r in picked.collect():
        near = _order((index.rotation, index.centroids, index.sizes), np.array([r.v]))[0]
        order[r.vec_id] = {int(x): i for i, x in enumerate(near)}
    depth = sorted(order[r.query_id][r.list] for r in truth)
    return depth[min(len(depth) - 1, int(np.ceil(target * len(depth))))] + 1 if depth else 1


def recall(found: DataFrame, truth: DataFrame) -> float:
    """Share of the true neighbours that were found."""
    n = truth.count()
    return found.join(truth.select("query_id", "vec_id"), ["query_id", "vec_id"], "left_semi").count() / n if n else 1.0
