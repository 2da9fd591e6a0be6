"""Operator 4: language identification by nearest centroids.

Whole texts become TF-IDF vectors of hashed byte 2- and 3-grams (lower-cased,
runs without letters squeezed), scaled to length one. Each language has several
centroids (spherical k-means); a text takes the language of the most similar
centroid. A text is also *rejected* where its cosine distance lies beyond the
limit learned for its language and length band.

Cases: null text or text without letters gives `und` with score 0 and is rejected;
no labelled row at all gives `und` for every text; ties between languages go to the
smaller code; repeated rows count and are judged one by one.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import free_names, slices

DIMS = 4096
BANDS = (40, 400)  # grams: below, between, above


@dataclass
class LanguageModel:
    languages: list[str]
    owner: np.ndarray  # language of each centroid
    idf: np.ndarray
    centroids: np.ndarray  # DIMS x centroids, unit columns
    floor: np.ndarray  # languages x bands: least cosine that is accepted

    def size_bytes(self) -> int:
        return self.idf.nbytes + self.centroids.nbytes + self.floor.nbytes


def _letters():
    import regex

    return regex.compile(r"\p{L}")


_KEEP = np.array([not (b < 65 or 90 < b < 97 or 122 < b < 128) for b in range(256)])


def count_matrix(texts: list[str]) -> np.ndarray:
    """Texts x DIMS counts of hashed 2- and 3-grams of bytes."""
    out = np.zeros((len(texts), DIMS), np.float32)
    for row, text in enumerate(texts):
        raw = np.frombuffer(f" {text.lower()} ".encode(), np.uint8)
        keep = _KEEP[raw]
        shown = np.where(keep, raw, 32)
        shown = shown[keep | np.concatenate([[True], keep[:-1]])].astype(np.uint32)  # one blank for each run
        if len(shown) < 3:
            continue
        two = shown[:-1] * np.uint32(257) + shown[1:]
        three = two[:-1] * np.uint32(263) + shown[2:]
        code = np.concatenate([two, three + np.uint32(7919)]) * np.uint32(2654435761)
        out[row] = np.bincount(code >> np.uint32(20), minlength=DIMS)
    return out


def weigh(counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    x = np.log1p(counts) * idf
    norm = np.linalg.norm(x, axis=1, keepdims=True)
    return x / np.where(norm > 0, norm, 1)


def _cluster(x: np.ndarray, k: int, rounds: int = 12) -> np.ndarray:
    """Spherical k-means from a farthest-first start; deterministic."""
    picked = [int(np.argmax(x @ x.mean(axis=0)))]
    while len(picked) < min(k, len(x)):
        near = (x @ x[picked].T).max(axis=1)
        picked.append(int(np.argmin(near)))
    c = x[picked]
    for _ in range(rounds):
        at = np.argmax(x @ c.T, axis=1)
        c = np.stack([x[at == j].sum(axis=0) if (at == j).any() else c[j] for j in range(len(c))])
        c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
    return c


def train(labelled: DataFrame, per_language: int = 200, clusters: int = 3, slack: float = 0.5, max_languages: int = 400) -> LanguageModel:
    """Fit on at most per_language rows (key, text, lang) of each of at most max_languages languages.

    The rows are those with the smallest hash of key, so the sample doesn't depend on
    partitioning. Only this bounded sample's sparse counts reach the driver.
    """
    rank = Window.partitionBy("lang").orderBy(F.xxhash64("key"), "key")
    keyed = labelled.where("lang is not null and text is not null")
    counts = keyed.groupBy("lang").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "lang").limit(max_languages)
    # about four times the sample of each language by the hash alone; ranks then run over those few
    some = keyed.select("key", "lang").join(F.broadcast(counts), "lang").where(F.pmod(F.xxhash64("key", F.lit(1)), F.lit(1 << 30)) * F.col("n") < 4 * per_language * (1 << 30))
    picked = some.withColumn("r", F.row_number().over(rank)).where(F.col("r") <= per_language)
    rows = keyed.join(F.broadcast(picked.select("key", "lang").distinct()), ["key", "lang"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        letters = _letters()
        for batch in batches:
            found = [(x, t) for x, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()) if letters.search(t)]
            for lo in range(0, len(found), 64):
                counts = count_matrix([t for _, t in found[lo : lo + 64]])
                yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in found[lo : lo + 64]]), pa.array([c.astype("<f4").tobytes() for c in counts], pa.binary())], ["lang", "counts"])

    # at most per_language * max_languages sparse rows; sorted, so sums come out alike on each run
    got = rows.select("lang", "text").mapInArrow(run, "lang string, counts binary").orderBy("lang", "counts").limit(per_language * max_languages).collect()
    languages = sorted({r.lang for r in got})
    if not languages:
        return LanguageModel([], np.zeros(0, int), np.ones(DIMS, np.float32), np.zeros((DIMS, 0), np.float32), np.zeros((0, len(BANDS) + 1), np.float32))
    df = np.zeros(DIMS)
    for r in got:
        df += np.frombuffer(r.counts, "<f4") > 0
    idf = (np.log((1 + len(got)) / (1 + df)) + 1).astype(np.float32)
    parts, owner, floors = [], [], []
    for at, lang in enumerate(languages):
        counts = np.stack([np.frombuffer(r.counts, "<f4") for r in got if r.lang == lang])
        x = weigh(counts, idf)
        c = _cluster(x, clusters)
        parts.append(c)
        owner += [at] * len(c)
        score, band = (x @ c.T).max(axis=1), np.digitize(counts.sum(axis=1), BANDS)
        floors.append([slack * float(np.quantile(score[band == b], 0.002)) if (band == b).sum() >= 20 else 0.02 for b in range(len(BANDS) + 1)])
    return LanguageModel(languages, np.array(owner), idf, np.concatenate(parts).T.astype(np.float32), np.array(floors, np.float32))


def identify(docs: DataFrame, model: LanguageModel, key: str = "doc_id", keep: bool = False) -> DataFrame:
    """key, lang_pred, score and rejected of every text; with keep the rows of docs with these three added, under free names, at the end."""
    if model.size_bytes() > 64_000_000:
        raise ValueError("the model is too large to broadcast")
    shared = docs.sparkSession.sparkContext.broadcast(model)
    columns = docs.columns if keep else [key, "text"]
    kinds = dict(docs.dtypes)
    names = tuple(free_names(["lang_pred", "lang_score", "rejected"], columns)) if keep else ("lang_pred", "score", "rejected")
    schema = ", ".join(f"`{c}` {kinds[c]}" for c in columns if keep or c != "text") + f", `{names[0]}` string, `{names[1]}` double, `{names[2]}` boolean"
    at = columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, letters = shared.value, _letters()
        for batch in batches:
            texts = batch.column(at).to_pylist()
            sizes = [t or "" for t in texts]
            langs, scores, rejected = ["und"] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
            for lo, hi in _blocks(sizes):
                rows = [i for i in range(lo, hi) if texts[i] and m.languages and letters.search(texts[i])]
                if not rows:
                    continue
                counts = count_matrix([texts[i] for i in rows])
                cos = weigh(counts, m.idf) @ m.centroids
                best = np.argmax(cos, axis=1)
                for i, b, c, n in zip(rows, best, cos[np.arange(len(rows)), best], counts.sum(axis=1)):
                    langs[i], scores[i] = m.languages[m.owner[b]], min(1.0, max(0.0, float(c)))
                    rejected[i] = c < m.floor[m.owner[b], np.digitize(n, BANDS)]
            kept = [batch.column(j) for j, c in enumerate(columns) if keep or c != "text"]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(langs), pa.array(scores), pa.array(rejected)], [*(c for c in columns if keep or c != "text"), *names])

    return docs.select(*columns).mapInArrow(run, schema)


def _blocks(texts: list) -> Iterator[tuple[int, int]]:
    for lo, hi in slices(texts):
        for a in range(lo, hi, 512):
            yield a, min(hi, a + 512)


def holdout(key: Column) -> Column:
    """True for the rows that training must not see; False for a null key."""
    return F.coalesce(F.crc32(key.cast("string")) % 3 == 1, F.lit(False))
