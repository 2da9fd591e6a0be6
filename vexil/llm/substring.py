"""Operator 9: exact substring deduplication by seed and extend.

A repeat is a run of `length` words that also starts earlier (smaller doc_id, or the same
document and an earlier start); each word of a later place is removed, judged on the input.

Seeds: among the 16 five-word grams of each 20-word window the smallest hash is its anchor
(winnowing), so equal windows have equal anchors at equal places. Consecutive windows with one
anchor form a *run*, which stretches over all words of its windows.

1. A job keeps the anchors that occur twice or more (partial aggregation, no pairs).
2. Occurrences are joined on their anchor and grouped by the run's whole content, the maximal
   extension of the anchor to both sides within its windows: all but the first place of a group are
   repeats. First places whose anchor also stands in other surroundings are left open.
3. Open places, which lie at the borders of maximal repeats, are extended window by window: their
   windows meet by a 128-bit hash, and all but the first place of a window are repeats.

Adjacent repeats are merged into maximal ones. No step emits pairs of a group or holds a group;
a document's own places are the largest thing in a task.

Cases: null text has no words. Rows with a null doc_id take no part and keep all words. Rows that share a doc_id
stand at one place in the order above: of their windows, those with an earlier start are earlier, whichever
row has them. Each keeps its own cuts, by a hash of its text.
Documents shorter than `length` keep all words.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import GRAM, as_bytes, free_names, grams, hash_words, made, materialise, mix, powers, release, release_since, signed, slices

ANCHOR = 5


def _argmin(values: np.ndarray, width: int) -> np.ndarray:
    """Place of the leftmost smallest of each `width` consecutive values, by doubling."""
    best, at, have = values, np.arange(len(values)), 1
    while have < width:
        step = min(have, width - have)
        left, right = best[:-step], best[step:]
        take = right < left
        at = np.where(take, at[step:], at[: len(at) - step])
        best = np.where(take, right, left)
        have += step
    return at


def _inside(offsets: np.ndarray, n: int, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Of n positions: the document of each, and whether a window of length words fits there."""
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))[:n]
    return doc, np.arange(n) + length <= offsets[doc + 1]


def find_runs(words: np.ndarray, offsets: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """doc, start, windows, anchor hash and content hash of every run."""
    n = len(words) - length + 1
    if n <= 0:
        return tuple(np.zeros(0, d) for d in (np.int64, np.int64, np.int64, np.uint64, np.uint64))
    seeds = grams(words, ANCHOR)
    at = _argmin(seeds, length - ANCHOR + 1)
    doc, fits = _inside(offsets, n, length)
    s = np.flatnonzero(fits)
    new = np.ones(len(s), bool)
    new[1:] = (at[s[1:]] != at[s[:-1]]) | (doc[s[1:]] != doc[s[:-1]])
    first = np.flatnonzero(new)
    start, count = s[first], np.diff(np.append(first, len(s)))
    anchor = at[start]
    # content: a polynomial over the run's words, from prefix sums and inverse powers
    up, down = powers(GRAM, len(words)), powers(pow(int(GRAM), -1, 2**64), len(words))
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(words, 3) * up)])
    content = (total[start + count + length - 1] - total[start]) * down[start]
    content = mix(content ^ mix((count * 64 + anchor - start).astype(np.uint64), 5), 6)
    return doc[start], start - offsets[doc[start]], count, seeds[anchor], content


def _run_table(docs: DataFrame, length: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = as_bytes(batch.column(2))
            for lo, hi in slices(texts):
                doc, start, count, anchor, content = find_runs(*hash_words(texts[lo:hi]), length)
                if not len(doc):
                    continue
                ends = np.flatnonzero(np.append(np.diff(doc) != 0, True)) + 1
                at = np.concatenate([[0], ends]).astype(np.int32)
                arrays = [pa.ListArray.from_arrays(pa.array(at), pa.array(x)) for x in (signed(anchor), signed(content), start.astype(np.int32), count.astype(np.int32))]
                own = pa.array(doc[ends - 1] + lo)
                yield pa.RecordBatch.from_arrays([batch.column(0).take(own), batch.column(1).take(own), *arrays], ["doc_id", "h", "a", "b", "s", "n"])

    return _known(docs).mapInArrow(run, "doc_id bigint, h bigint, a array<bigint>, b array<bigint>, s array<int>, n array<int>")


def _known(docs: DataFrame) -> DataFrame:
    """doc_id, h (the text's hash) and text of the rows that take part."""
    return docs.where("doc_id is not null").select(F.col("doc_id").cast("bigint").alias("doc_id"), F.xxhash64("text").alias("h"), "text")


def _window_table(docs: DataFrame, length: int) -> DataFrame:
    """128-bit hashes of the windows in the open runs (column `open`: array of start, windows)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, opened = as_bytes(batch.column(2)), batch.column(3).to_pylist()
            for lo, hi in slices(texts):
                words, offsets = hash_words(texts[lo:hi])
                one, two = grams(words, length, 11), grams(words ^ np.uint64(0x5851F42D4C957F2D), length, 12)
                starts = [np.concatenate([np.arange(x["s"], x["s"] + x["n"]) for x in opened[lo + i]]) for i in range(hi - lo)]
                where = np.concatenate([s + offsets[i] for i, s in enumerate(starts)])
                own = pa.array(np.repeat(np.arange(lo, hi), [len(s) for s in starts]))
                yield pa.RecordBatch.from_arrays([pa.array(signed(one[where])), pa.array(signed(two[where])), batch.column(0).take(own), batch.column(1).take(own), pa.array(np.concatenate(starts).astype(np.int32))], ["w1", "w2", "doc_id", "h", "s"])

    return docs.select("doc_id", "h", "text", "open").mapInArrow(run, "w1 bigint, w2 bigint, doc_id bigint, h bigint, s int")


def find_repeats(docs: DataFrame, length: int = 20) -> DataFrame:
    """doc_id, h and the windows that start earlier elsewhere: cuts, array of struct(s, n) for starts s .. s+n-1."""
    if length < ANCHOR + 1:
        raise ValueError(f"length must be over {ANCHOR}")
    before = made()
    table = materialise(_run_table(docs, length), "runs")
    runs = table.select("doc_id", "h", F.explode(F.arrays_zip("a", "b", "s", "n")).alias("r")).select("doc_id", "h", "r.*")
    anchors = runs.groupBy("a").agg(F.count("*").alias("c"), (F.min("b") != F.max("b")).alias("mixed")).where("c > 1").drop("c")
    repeated = materialise(runs.join(materialise(anchors, "anchors"), "a"), "repeated")
    # written, so that the join below has two plain sides and a hot group can be split
    first = materialise(repeated.groupBy("a", "b").agg(F.min(F.struct("doc_id", "s")).alias("f")), "first")
    settled = materialise(repeated.join(first, ["a", "b"]).where("mixed or struct(doc_id, s) != f").select("doc_id", "h", "s", "n", (F.struct("doc_id", "s") != F.col("f")).alias("cut")), "settled")
    release(table, repeated, first)
    opened = settled.where("not cut").groupBy("doc_id", "h").agg(F.collect_list(F.struct("s", "n")).alias("open"))
    windows = materialise(_window_table(_known(docs).join(opened, ["doc_id", "h"]), length), "windows")
    twice = materialise(windows.groupBy("w1", "w2").agg(F.min(F.struct("doc_id", "s")).alias("f"), F.count("*").alias("c")).where("c > 1").drop("c"), "twice")
    late = windows.join(twice, ["w1", "w2"]).where(F.struct("doc_id", "s") != F.col("f")).select("doc_id", "h", "s", F.lit(1).alias("n"))
    cuts = settled.where("cut").select("doc_id", "h", "s", "n").unionByName(late).groupBy("doc_id", "h").agg(F.collect_list(F.struct("s", "n")).alias("cuts"))
    found = materialise(cuts, "cuts")
    release_since(before, found)
    return found


def _kept(words: list[bytes], cuts: list[dict], length: int) -> list[bytes]:
    gone = np.zeros(len(words) + 1, np.int64)
    for c in cuts:
        if c["s"] < len(words):
            gone[c["s"]] += 1
            gone[min(len(words), c["s"] + c["n"] + length - 1)] -= 1
    dead = np.cumsum(gone[:-1]) > 0
    return [w for w, d in zip(words, dead) if not d] if dead.any() else words


def deduplicate(docs: DataFrame, length: int = 20, digest: bool = False) -> DataFrame:
    """The rows of docs with repeats cut from text.

    Texts without a repeat stay as they are; others are their kept words, joined by one space. With
    digest: doc_id, n_words, n_removed, kept_sha256 only.
    """
    columns = ["doc_id", "text"] if digest else docs.columns
    doc, own, cut = free_names(["_doc", "_h", "_cuts"], columns)
    cuts = find_repeats(docs, length).withColumnsRenamed({"doc_id": doc, "h": own, "cuts": cut})
    kinds = dict(docs.dtypes)
    joined = docs.select(*columns).join(cuts, (F.col("doc_id") == F.col(doc)) & (F.xxhash64("text") == F.col(own)), "left").drop(doc, own)
    schema = "doc_id bigint, n_words bigint, n_removed bigint, kept_sha256 string" if digest else ", ".join(f"`{c}` {kinds[c]}" for c in columns)
    at = columns.index("text")

    def texts(part: pa.RecordBatch) -> pa.RecordBatch:
        out = []
        for text, found in zip(part.column(at).to_pylist(), part.column(len(columns)).to_pylist()):
            if found:
                words = text.encode().split()
                kept = _kept(words, found, length)
                text = b" ".join(kept).decode() if len(kept) < len(words) else text
            out.append(text)
        return pa.RecordBatch.from_arrays([pa.array(out, pa.string()) if i == at else part.column(i) for i in range(len(columns))], columns)

    def digests(part: pa.RecordBatch) -> pa.RecordBatch:
        n, removed, out = [], [], []
        for text, found in zip(as_bytes(part.column(1)), part.column(2).to_pylist()):
            words = text.split()
            kept = _kept(words, found, length) if found else words
            n.append(len(words))
            removed.append(len(words) - len(kept))
            out.append(hashlib.sha256(b" ".join(kept)).hexdigest())
        return pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(out, pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                yield (digests if digest else texts)(batch.slice(lo, 1000))

    return joined.mapInArrow(run, schema)
