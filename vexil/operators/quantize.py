"""Quantized pre-filter: filter, approximate distances on codes, exact rerank of the best few.

Codes: product (`pq`), product after a learned rotation (`opq`), one bit per rotated coordinate with an unbiased
inner-product estimate (`onebit`), and several bits per coordinate on a uniform grid (`multibit`).
Codebooks are fitted on a bounded sample and broadcast; every row is coded.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import block_distances, pair_distances, slack
from ..functions.predicates import Constraint, constraint
from ..sources.store import written
from .exact import CELLS, Nearest, QueryBlock, least, matrix, query_parts, top_k

KINDS = ("pq", "opq", "onebit", "multibit")


def lloyd(x: np.ndarray, k: int, rounds: int = 12, seed: int = 0) -> np.ndarray:
    """k-means with a fixed seed; empty clusters keep their centre."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        at = np.argmin((c * c).sum(axis=1) - 2 * x @ c.T, axis=1)
        sums, n = np.zeros_like(c), np.bincount(at, minlength=len(c))
        np.add.at(sums, at, x)
        c = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], c)
    return c


@dataclass
class Codec:
    kind: str
    rotation: np.ndarray
    centre: np.ndarray
    books: list[np.ndarray]  # per part: centroids
    cuts: list[tuple[int, int]]
    bits: int
    low: float = 0.0
    step: float = 1.0

    def turn(self, x: np.ndarray) -> np.ndarray:
        return (x - self.centre) @ self.rotation

    def encode(self, x: np.ndarray) -> np.ndarray:
        """Rows of bytes."""
        y = self.turn(x)
        if self.kind in ("pq", "opq"):
            return np.stack([np.argmin((b * b).sum(axis=1) - 2 * y[:, lo:hi] @ b.T, axis=1) for b, (lo, hi) in zip(self.books, self.cuts)], axis=1).astype(np.uint8)
        norm = np.linalg.norm(y, axis=1)
        unit = y / np.where(norm > 0, norm, 1)[:, None]
        levels = (unit > 0).astype(np.uint8) if self.kind == "onebit" else np.clip(np.rint((unit - self.low) / self.step), 0, 2**self.bits - 1).astype(np.uint8)
        packed = np.packbits(levels, axis=1) if self.kind == "onebit" else levels
        grid = self._grid(levels)
        dot = (grid * unit).sum(axis=1)  # how far the code reaches along its vector
        return np.concatenate([packed, np.stack([norm, dot], axis=1).astype("<f4").view(np.uint8).reshape(len(x), 8)], axis=1)

    def _grid(self, levels: np.ndarray) -> np.ndarray:
        if self.kind == "onebit":
            return (levels.astype(float) * 2 - 1) / np.sqrt(levels.shape[1])
        return self.low + levels * self.step

    def decode(self, codes: np.ndarray) -> np.ndarray:
        """Reconstruction in rotated space."""
        if self.kind in ("pq", "opq"):
            return np.concatenate([b[codes[:, i]] for i, b in enumerate(self.books)], axis=1)
        d = self.rotation.shape[1]
        norm, dot = codes[:, -8:].copy().view("<f4").astype(float).T
        levels = np.unpackbits(codes[:, :-8], axis=1)[:, :d] if self.kind == "onebit" else codes[:, :-8]
        grid = self._grid(levels)
        return grid * (norm / np.where(dot > 1e-9, dot, 1))[:, None]

    def distances(self, codes: np.ndarray, q: np.ndarray) -> np.ndarray:
        """Queries x rows of estimated squared distances."""
        p = self.turn(q)
        if self.kind in ("pq", "opq"):
            out = np.zeros((len(q), len(codes)))
            for i, (b, (lo, hi)) in enumerate(zip(self.books, self.cuts)):
                table = ((p[:, None, lo:hi] - b[None]) ** 2).sum(axis=2)
                out += table[:, codes[:, i]]
            return out
        norm = codes[:, -8:-4].copy().view("<f4").astype(float)[:, 0]
        return (p * p).sum(axis=1)[:, None] + (norm * norm)[None, :] - 2 * p @ self.decode(codes).T


def fit_codec(x: np.ndarray, kind: str = "pq", m: int = 8, bits: int = 4, seed: int = 0, rounds: int = 6) -> Codec:
    d = x.shape[1]
    rng = np.random.default_rng(seed)
    centre, rotation = x.mean(axis=0), np.eye(d)
    edges = np.linspace(0, d, min(m, d) + 1).astype(int)
    cuts = list(zip(edges[:-1].tolist(), edges[1:].tolist()))

    def books(y: np.ndarray) -> list[np.ndarray]:
        return [lloyd(y[:, lo:hi], 2**bits, seed=seed + i) for i, (lo, hi) in enumerate(cuts)]

    if kind == "pq":
        return Codec(kind, rotation, centre, books(x - centre), cuts, bits)
    rotation = np.linalg.qr(rng.normal(size=(d, d)))[0]
    if kind == "opq":
        for _ in range(rounds):
            codec = Codec(kind, rotation, centre, books((x - centre) @ rotation), cuts, bits)
            u, _, vt = np.linalg.svd((x - centre).T @ codec.decode(codec.encode(x)))
            rotation = u @ vt
        return Codec(kind, rotation, centre, books((x - centre) @ rotation), cuts, bits)
    reach = 3 / np.sqrt(d)
    return Codec(kind, rotation, centre, [], cuts, 1 if kind == "onebit" else bits, -reach, 2 * reach / (2**bits - 1))


@dataclass
class QuantizedIndex:
    codes: DataFrame  # id, labels, vec, code
    base: DataFrame
    codec: Codec


def sample_vectors(base: DataFrame, rows: int, seed: int = 1) -> np.ndarray:
    """At most `rows` vectors, the first by hash of id."""
    seen = base.select("vec", F.xxhash64("id", F.lit(seed)).alias("h")).orderBy("h", "vec").limit(rows).collect()
    return np.array([r.vec for r in seen], float) if seen else np.zeros((1, 1))


def code_rows(base: DataFrame, codec: Codec, keep: list[str]) -> DataFrame:
    shared = base.sparkSession.sparkContext.broadcast(codec)
    kinds = dict(base.dtypes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            code = [c.tobytes() for c in shared.value.encode(x)] if batch.num_rows else []
            yield pa.RecordBatch.from_arrays([*(batch.column(i + 1) for i in range(len(keep))), pa.array(code, pa.binary())], [*keep, "code"])

    return base.select(F.col("vec").alias("_coded"), *keep).mapInArrow(run, ", ".join(f"{c} {kinds[c]}" for c in keep) + ", code binary")


def fit(base: DataFrame, kind: str = "pq", m: int = 8, bits: int = 4, seed: int = 0, sample: int = 20_000) -> QuantizedIndex:
    codec = fit_codec(sample_vectors(base, sample), kind, m, bits, seed)
    return QuantizedIndex(written(code_rows(base, codec, ["id", "labels", "vec"]), "codes"), base, codec)


def code_bytes(codes: pa.BinaryArray) -> np.ndarray:
    return np.frombuffer(b"".join(codes.to_pylist()), np.uint8).reshape(len(codes), -1)


def pooled(block: QueryBlock, codec: Codec, passing: Iterator[tuple[np.ndarray, np.ndarray]], codes: np.ndarray, pool: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """A matrix at a time: positions of queries and of rows, code distances, and True at the pool best passing rows of each query (more only at a tie)."""
    for own, rows in passing:
        for lo in range(0, len(own), max(1, CELLS // len(rows))):
            some = own[lo : lo + max(1, CELLS // len(rows))]
            dist = codec.distances(codes[rows], block.q[some])
            yield some, rows, dist, dist <= least(dist, pool)[:, None]


def add_pooled(best: Nearest, block: QueryBlock, codec: Codec, batch: pa.RecordBatch, passing: Iterator[tuple[np.ndarray, np.ndarray]], k: int, pool: int) -> None:
    """Exact distances of the pool best by code of a batch (id, labels, code, vec), as far as they may be among the k nearest."""
    ids, x = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64), matrix(batch.column(3))
    xt, qt = np.ascontiguousarray(x.T), np.ascontiguousarray(block.q.T)
    for own, rows, _, hit in pooled(block, codec, passing, code_bytes(batch.column(2)), pool):
        if hit.mean() > 0.02:  # a wide pool: a matrix product of the vectors leaves out what can't be among the k nearest
            dist = np.where(hit, block_distances(x[rows], block.q[own]), np.inf)
            hit &= dist <= (np.minimum(best.bound(own), least(dist, k)) + 2 * slack(x[rows], block.q[own]))[:, None]
        row, col = np.nonzero(hit)
        best.add(own[row], ids[rows[col]], pair_distances(xt, qt, rows[col], own[row]))


def scan(codes: DataFrame, codec: Codec, queries: DataFrame, scenario: str, pool: int) -> DataFrame:
    """qid, id, approx: the pool best passing rows of each query by code distance."""
    shared = codes.sparkSession.sparkContext.broadcast((codec, QueryBlock(queries)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code, block = shared.value
        for batch in batches:
            if batch.num_rows and len(block.qid):
                for own, rows, dist, hit in pooled(block, code, block.passing(batch.column(1), scenario), code_bytes(batch.column(2)), pool):
                    row, col = np.nonzero(hit)
                    yield pa.RecordBatch.from_arrays([pa.array(block.qid[own[row]]), batch.column(0).take(pa.array(rows[col])), pa.array(dist[row, col])], ["qid", "id", "approx"])

    best = codes.select("id", "labels", "code").mapInArrow(run, "qid bigint, id bigint, approx double")
    order = Window.partitionBy("qid").orderBy("approx", "id")
    return best.withColumn("r", F.row_number().over(order)).where(F.col("r") <= pool).drop("r")


def scan_exact(codes: DataFrame, codec: Codec, queries: DataFrame, scenario: str, k: int, pool: int) -> DataFrame:
    """qid, id, dist: of each Arrow batch, the pool best passing rows by code distance are scored exactly where they lie; a task returns the k nearest of these."""
    shared = codes.sparkSession.sparkContext.broadcast((codec, QueryBlock(queries)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code, block = shared.value
        best = Nearest(len(block.qid), k)
        for batch in batches:
            if batch.num_rows and len(block.qid):
                add_pooled(best, block, code, batch, block.passing(batch.column(1), scenario), k, pool)
        yield from best.rows(block.qid)

    return codes.select("id", "labels", "code", "vec").mapInArrow(run, "qid bigint, id bigint, dist double")


def search(index: QuantizedIndex, queries: DataFrame, of: str | Constraint, k: int, pool: int | None = None, reranked: bool = True) -> DataFrame:
    """pool candidates by codes (default 4 k) of each Arrow batch, then exact distances; without rerank the estimates are the distances."""
    if reranked:
        found = [scan_exact(index.codes, index.codec, part, constraint(of).name, k, pool or 4 * k) for part in query_parts(queries, k)]
        return top_k(reduce(DataFrame.unionByName, found), k)
    found = scan(index.codes, index.codec, queries, constraint(of).name, pool or 4 * k)
    order = Window.partitionBy("qid").orderBy("approx", "id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("qid", "rank", "id", F.col("approx").alias("dist"))


def reconstruction_error(base: DataFrame, codec: Codec, sample: int = 5_000) -> float:
    """Mean squared error of decoded vectors on a sample, relative to their variance."""
    x = sample_vectors(base, sample, 2)
    y = codec.turn(x)
    return float(((codec.decode(codec.encode(x)) - y) ** 2).sum() / max(1e-12, (y**2).sum()))
