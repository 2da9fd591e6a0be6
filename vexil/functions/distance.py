"""Distances: exact folds inside the JVM, the Arrow block kernel, and SQL functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def l2sq(a: Column, b: Column) -> Column:
    """Squared Euclidean distance, summed in order in double precision."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x)


def inner(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def negative_inner(a: Column, b: Column) -> Column:
    return -inner(a, b)


def cosine(a: Column, b: Column) -> Column:
    """1 - cosine similarity; 1 if a vector is zero."""
    norm = F.sqrt(inner(a, a) * inner(b, b))
    return F.when(norm > 0, 1 - inner(a, b) / norm).otherwise(F.lit(1.0))


METRICS = {"l2": l2sq, "cosine": cosine, "ip": negative_inner}


def hamming(a: Column, b: Column) -> Column:
    """Positions in which two label vectors differ."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x != y).cast("int")), F.lit(0), lambda s, x: s + x)


def fused(distance: Column, differ: Column, positions: int, weight: float, additive: bool = False) -> Column:
    """Distance fused with label difference: distance * (1 + weight * share), or distance + weight * differ."""
    return distance + weight * differ if additive else distance * (1 + weight * differ / positions)


def block_distances(x: np.ndarray, q: np.ndarray, metric: str = "l2") -> np.ndarray:
    """Queries x rows, by one matrix product; for candidates, not for final scores."""
    dot = q @ x.T
    if metric == "ip":
        return -dot
    if metric == "cosine":
        norm = np.linalg.norm(q, axis=1)[:, None] * np.linalg.norm(x, axis=1)[None, :]
        return 1 - np.divide(dot, norm, out=np.zeros_like(dot), where=norm > 0)
    dot *= -2
    dot += (q * q).sum(axis=1)[:, None]
    dot += (x * x).sum(axis=1)[None, :]
    return dot


def pair_distances(xt: np.ndarray, qt: np.ndarray, col: np.ndarray, row: np.ndarray, metric: str = "l2") -> np.ndarray:
    """Distances of the pairs (col of xt, row of qt), both with a vector per column. Summed in order like the folds above, so that both give the same bits."""

    def fold(a: np.ndarray, at: np.ndarray, b: np.ndarray, bt: np.ndarray, of) -> np.ndarray:
        total = np.zeros(len(at))
        for j in range(len(a)):
            total += of(a[j][at], b[j][bt])
        return total

    if metric == "l2":
        return fold(xt, col, qt, row, lambda x, y: (x - y) * (x - y))
    dot = fold(xt, col, qt, row, np.multiply)
    if metric == "ip":
        return -dot
    norm = np.sqrt(fold(xt, col, xt, col, np.multiply) * fold(qt, row, qt, row, np.multiply))
    return np.where(norm > 0, 1 - np.divide(dot, norm, out=np.zeros_like(dot), where=norm > 0), 1.0)


def slack(x: np.ndarray, q: np.ndarray, metric: str = "l2") -> np.ndarray:
    """More than block_distances of a query's row can be off, for each query."""
    if metric == "cosine" or not len(x):
        return np.full(len(q), 1e-9)
    return 1e-10 * ((q * q).sum(axis=1) + (x * x).sum(axis=1).max())


SQL_FUNCTIONS = {
    "l2sq": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)",
    "cosine_distance": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN 1 - aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x) / sqrt(aggregate(a, 0D, (s, x) -> s + x * x) * aggregate(b, 0D, (s, x) -> s + x * x))",
    "labels_contain": "(f ARRAY<INT>, q ARRAY<INT>) RETURNS BOOLEAN RETURN size(array_except(q, f)) = 0",
    "labels_overlap": "(f ARRAY<INT>, q ARRAY<INT>) RETURNS BOOLEAN RETURN arrays_overlap(f, q)",
    "hamming_distance": "(a ARRAY<INT>, b ARRAY<INT>) RETURNS INT RETURN aggregate(zip_with(a, b, (x, y) -> int(x != y)), 0, (s, x) -> s + x)",
}


def register_sql(spark: SparkSession) -> None:
    """SQL functions that Catalyst inlines; for users of spark.sql."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")


DISTANCE_SQL = "list_reduce(list_transform(list_zip(vec, qvec), lambda z: (z[1]-z[2])*(z[1]-z[2])), lambda a, b: a + b)"
