"""Operator 3: pack token ids into fixed-length rows and write them as binary matrices.

Documents are encoded, an end token is added, and a document longer than a row is split
without loss into row-long segments and a rest. Segments are packed best-fit-decreasing: each goes to
the open row with the least room that holds it, found with a segment tree over room sizes
(how many open rows have exactly r tokens left), in O(log row length). Rows are padded at the end.

Documents are dealt by hash to shards of a bounded number of tokens in expectation; each shard packs
on its own, so memory follows the shard size, a lost executor costs its shards only, and the outcome
doesn't depend on partitioning. A shard's order is (length, doc_id, segment), so ties are defined.

Cases: null or empty text yields the end token alone; a null doc_id is packed and listed as null;
rows that share a doc_id are packed one by one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import TreeEncoder
from .common import materialise


class RoomTree:
    """Counts open rows by tokens left; finds the smallest room that is at least n."""

    def __init__(self, size: int):
        self.leaves = 1 << size.bit_length()
        self.count = [0] * (2 * self.leaves)

    def add(self, room: int, by: int) -> None:
        i = room + self.leaves
        while i:
            self.count[i] += by
            i >>= 1

    def fit(self, n: int) -> int | None:
        i = n + self.leaves
        if self.count[i]:
            return n
        while i > 1:  # up to the first right neighbour with an open row, then down its left edge
            if not i & 1 and self.count[i + 1]:
                i += 1
                while i < self.leaves:
                    i = 2 * i if self.count[2 * i] else 2 * i + 1
                return i - self.leaves
            i >>= 1
        return None


def best_fit_decreasing(lengths: list[int], width: int) -> list[list[int]]:
    """Rows of item numbers; lengths must come in falling order and be at most width."""
    tree, rows, open_rows = RoomTree(width), [], {}
    for item, n in enumerate(lengths):
        room = tree.fit(n) if n else None
        if room is None or not room:
            rows.append([item])
            room, row = width, len(rows) - 1
        else:
            row = open_rows[room].pop()
            rows[row].append(item)
            tree.add(room, -1)
        if room - n:
            open_rows.setdefault(room - n, []).append(row)
            tree.add(room - n, 1)
    return rows


def pack_lists(docs: list[tuple[int | None, np.ndarray]], width: int, pad: int, kind: str = "<u2") -> tuple[np.ndarray, list[list[int]], list[list[int | None]], list[list[int]]]:
    """Matrix of ids, and for each row: cumulative segment lengths from 0, doc_ids, segment numbers."""
    parts = [(doc, k, ids[lo : lo + width]) for doc, ids in docs for k, lo in enumerate(range(0, len(ids), width))]
    parts.sort(key=lambda p: (-len(p[2]), p[0] is None, p[0] or 0, p[1]))
    rows = best_fit_decreasing([len(p[2]) for p in parts], width)
    matrix = np.full((len(rows), width), pad, kind)
    cumulative, ids, numbers = [], [], []
    for r, items in enumerate(rows):
        at = np.concatenate([[0], np.cumsum([len(parts[i][2]) for i in items])])
        matrix[r, : at[-1]] = np.concatenate([parts[i][2] for i in items])
        cumulative.append(at.tolist())
        ids.append([parts[i][0] for i in items])
        numbers.append([parts[i][1] for i in items])
    return matrix, cumulative, ids, numbers


def positions(cumulative: list[int], width: int) -> np.ndarray:
    """Position ids of a packed row: they restart at each segment; padding has 0."""
    out = np.zeros(width, np.uint16)
    for a, b in zip(cumulative[:-1], cumulative[1:]):
        out[a:b] = np.arange(b - a)
    return out


SCHEMA = "shard bigint, row int, n_tokens int, ids binary, cu_seqlens array<int>, position_resets array<int>, doc_ids array<bigint>, segments array<int>"


def _kind(bits: int) -> str:
    if bits not in (16, 32):
        raise ValueError("ids have 16 or 32 bits")
    return f"<u{bits // 8}"


def encode_ids(docs: DataFrame, vocabulary: str, end: int, special: dict[str, int] | None = None, bits: int = 16) -> DataFrame:
    """doc_id and ids (little-endian, end token added) of every document; vocabularies over 65,536 entries take 32 bits."""
    kind = _kind(bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = TreeEncoder(vocabulary, special)
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                ids = [np.array([*encoder.encode(t or ""), end], kind).tobytes() for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array(ids, pa.binary())], ["doc_id", "ids"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, ids binary")


def pack(encoded: DataFrame, width: int = 2048, pad: int = 50256, shard_tokens: int = 1_000_000, seed: int = 3, bits: int = 16) -> DataFrame:
    """SCHEMA rows from (doc_id, ids binary). position_resets are the starts of the row's segments.

    A document is cut into row-long segments before the shuffle, so a shard never has to take a
    very long document whole; full segments need no packing.
    """
    if not 0 < width < 65536:
        raise ValueError("width must fit 16 bits")
    kind, each = _kind(bits), bits // 8
    total = (encoded.agg(F.sum(F.length("ids"))).first()[0] or 0) // each
    shards = max(1, -(-total // shard_tokens))
    cut = F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((F.length("ids") / each - 1) / width)).cast("int")), lambda k: F.struct(k.alias("k"), F.substr("ids", k * (each * width) + 1, F.lit(each * width)).alias("part")))
    parts = encoded.select("doc_id", F.explode(cut).alias("p")).select("doc_id", "p.*")
    shard = F.pmod(F.xxhash64(F.coalesce("doc_id", F.lit(-1)), "k", F.length("part"), F.xxhash64("part"), F.lit(seed)), F.lit(shards))

    def run(key: tuple, table: pa.Table) -> pa.Table:
        docs = sorted(zip(table["doc_id"].to_pylist(), table["k"].to_pylist(), table["part"].to_pylist()), key=lambda x: (x[0] is None, x[0] or 0, x[1], x[2]))
        lists = [(i, np.frombuffer(p, kind)) for i, (_, _, p) in enumerate(docs)]
        matrix, cumulative, items, _ = pack_lists(lists, width, pad, kind)
        n = len(matrix)
        columns = [
            pa.array([key[0].as_py()] * n, pa.int64()), pa.array(range(n), pa.int32()), pa.array([c[-1] for c in cumulative], pa.int32()), pa.array([m.tobytes() for m in matrix], pa.binary()),
            pa.array(cumulative, pa.list_(pa.int32())), pa.array([c[:-1] for c in cumulative], pa.list_(pa.int32())), pa.array([[docs[i][0] for i in x] for x in items], pa.list_(pa.int64())), pa.array([[docs[i][1] for i in x] for x in items], pa.list_(pa.int32())),
        ]
        return pa.Table.from_arrays(columns, ["shard", "row", "n_tokens", "ids", "cu_seqlens", "position_resets", "doc_ids", "segments"])

    return parts.withColumn("shard", shard.cast("bigint")).groupBy("shard").applyInArrow(run, SCHEMA)


def pack_documents(docs: DataFrame, vocabulary: str, end: int = 50256, special: dict[str, int] | None = None, width: int = 2048, shard_tokens: int = 1_000_000, bits: int = 16) -> DataFrame:
    encoded = materialise(encode_ids(docs, vocabulary, end, special, bits), "ids")
    return pack(encoded, width, end, shard_tokens, bits=bits)


def write_matrices(packed: DataFrame, path: str, bits: int = 16) -> None:
    """Write packed rows under path, one binary id matrix (rows joined) per shard beside its cumulative lengths and position ids."""
    each = bits // 8
    width = F.length("ids") / each

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in batches:
            frame["positions"] = [positions(list(c), len(i) // each).astype("<u2").tobytes() for c, i in zip(frame["cu_seqlens"], frame["ids"])]
            yield frame

    shown = packed.select("shard", "row", "ids", "cu_seqlens", width.cast("int").alias("width")).mapInPandas(run, "shard bigint, row int, ids binary, cu_seqlens array<int>, width int, positions binary")
    shown.repartition("shard").sortWithinPartitions("shard", "row").write.parquet(path)
