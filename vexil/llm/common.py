"""Shared pieces of the training-data operators: materialised tables and word hashing.

Word hashing works on the UTF-8 bytes of whole texts. A word is a maximal run of
bytes outside 0x20 and 0x09-0x0D; its 64-bit hash is a polynomial over random
byte codes, finished with a bijective mixer. All arithmetic wraps modulo 2**64.
"""

from __future__ import annotations

import atexit
import re
import tempfile
import threading
import uuid
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession

SLICE_BYTES = 2_000_000
WORD_RE = r"[^\x20\x09-\x0D]+"
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
_tables: list[tuple[SparkSession, str]] = []
_mine = threading.local()


def shared_dir(spark: SparkSession) -> str:
    """The folder the cluster shares (spark.checkpoint.dir); a temporary one only where it is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        made = spark.sparkContext._jsc.sc().getCheckpointDir()
        if made.isDefined():
            return made.get()
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the cluster shares")
        found = tempfile.mkdtemp(prefix="vexil-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def materialise(df: DataFrame, tag: str, batch: int | None = None) -> DataFrame:
    """Write df once to the shared folder and read it back: cuts lineage, survives lost executors.

    Shuffle files of the writing job are freed as soon as it ends, so a chain of
    steps needs the disk of its largest step, not of all of them. batch: rows of an Arrow batch, for
    steps with wide rows.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/vexil-{tag}-{uuid.uuid4().hex}"
    wanted = {_CLEANUP: "true"} | ({_BATCH: str(batch)} if batch else {})
    before = {k: spark.conf.get(k) for k in wanted}
    for k, v in wanted.items():
        spark.conf.set(k, v)
    try:
        df.write.parquet(path)
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    _tables.append((spark, path))
    _mine.__dict__.setdefault("paths", []).append(path)
    return spark.read.schema(df.schema).parquet(path)


def release(*frames: DataFrame) -> None:
    """Delete the files of materialised frames that no later step reads."""
    for df in frames:
        for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            hit = next((x for x in _tables if path.endswith(x[1].split("://")[-1].rstrip("/"))), None)
            if hit:
                _delete(*hit)
                _tables.remove(hit)


def made() -> set[str]:
    """Paths of the frames that this thread has materialised."""
    return set(_mine.__dict__.setdefault("paths", []))


def release_since(before: set[str], *kept: DataFrame) -> None:
    """Delete what this thread materialised after `before` was taken, but for the frames that later steps read."""
    held = {f.rsplit("/", 2)[-2] for df in kept for f in df.inputFiles()}
    gone = {path for path in made() - before if path.rsplit("/", 1)[-1] not in held}
    for hit in [t for t in _tables if t[1] in gone]:
        _delete(*hit)
        _tables.remove(hit)
    _mine.paths = [path for path in _mine.paths if path not in gone]


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _drop_tables() -> None:
    for spark, path in _tables:
        try:
            if spark.sparkContext._jsc is not None:
                _delete(spark, path)
        except Exception:  # noqa: BLE001  the session may be gone by now
            return


def free_names(wanted: list[str], taken: list[str]) -> list[str]:
    """The wanted column names, with underscores before those that are taken (letter case aside)."""
    held, out = {c.lower() for c in taken}, []
    for name in wanted:
        while name.lower() in held:
            name = f"_{name}"
        held.add(name.lower())
        out.append(name)
    return out


# ---------------------------------------------------------------- hashing

_rng = np.random.default_rng(20_240_611)
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_CODE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_CODE[_SPACE] = 0
_BASE = np.uint64(0x9E3779B97F4A7C15)
GRAM = np.uint64(0xD1342543DE82EF95)


def powers(base: int | np.uint64, n: int) -> np.ndarray:
    """base ** 0 .. base ** (n - 1) modulo 2**64."""
    steps = np.full(max(1, n), base, np.uint64)
    steps[0] = 1
    return np.cumprod(steps, dtype=np.uint64)


_LOW = powers(_BASE, 4096)


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """Bijective 64-bit finaliser."""
    x = x + np.uint64((salt * 0x9E3779B97F4A7C15) & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(pos: np.ndarray) -> np.ndarray:
    """_BASE ** pos from two small tables, so memory doesn't follow the longest word."""
    top = int(pos.max(initial=0)) >> 12
    if not top:
        return _LOW[pos]
    return _LOW[pos & 4095] * powers(_LOW[-1] * _BASE, top + 1)[pos >> 12]


def hash_words(docs: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of all docs in a row, and the offsets of each document's words."""
    sizes = np.fromiter((len(d) for d in docs), np.int64, len(docs))
    raw = np.frombuffer(b"\n".join(docs) + b"\n", np.uint8)
    ends_at = np.cumsum(sizes + 1)
    blank = _SPACE[raw]
    first = ~blank
    first[1:] &= blank[:-1]
    starts = np.flatnonzero(first)
    offsets = np.concatenate([[0], np.searchsorted(starts, ends_at)]).astype(np.int64)
    if not len(starts):
        return np.zeros(0, np.uint64), offsets
    codes = _CODE[raw[starts[0] :]]
    gaps = np.diff(np.append(starts, len(raw)))
    pos = np.arange(len(codes)) - np.repeat(starts - starts[0], gaps)
    return mix(np.add.reduceat(codes * _powers(pos), starts - starts[0])), offsets


def grams(words: np.ndarray, k: int, salt: int = 0) -> np.ndarray:
    """Hash of every k consecutive words (documents' borders are the caller's business)."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.zeros(n, np.uint64)
    for j in range(k):
        total = total * GRAM + words[j : j + n]
    return mix(total, salt + k)


def slices(rows: list[bytes], limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows of at most limit bytes, or of one longer row."""
    lo, held = 0, 0
    for i, x in enumerate(rows):
        if held and held + len(x) > limit:
            yield lo, i
            lo, held = i, 0
        held += len(x) + 1
    if lo < len(rows):
        yield lo, len(rows)


def as_bytes(column) -> list[bytes]:
    """An Arrow string column as UTF-8 bytes; null becomes empty."""
    import pyarrow as pa

    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def signed(x: np.ndarray) -> np.ndarray:
    """The same 64 bits as Spark's bigint."""
    return np.ascontiguousarray(x).view(np.int64)
