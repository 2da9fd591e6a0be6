"""Written tables: lineage cuts in the shared folder, and a versioned index store."""

from __future__ import annotations

import atexit
import re
import json
import tempfile
import time
import uuid
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_made: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a temporary folder only where it is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        set_before = spark.sparkContext._jsc.sc().getCheckpointDir()
        if set_before.isDefined():
            return set_before.get()
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the cluster shares")
        found = tempfile.mkdtemp(prefix="vexil-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def written(df: DataFrame, tag: str) -> DataFrame:
    """df written once as Parquet in the shared folder and read back; frees the job's shuffle files."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/vexil-{tag}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before)
    _made.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def written_in_slices(df: DataFrame, tag: str, key: str, slices: int) -> DataFrame:
    """df written slice by slice of the hashes of key, so that the shuffle files of one slice are on disk at a time. Each slice reads the sources again."""
    parts = [written(df.where(F.pmod(F.xxhash64(key), F.lit(slices)) == i) if slices > 1 else df, tag) for i in range(slices)]
    return reduce(DataFrame.unionByName, parts)


def _fs(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def delete(spark: SparkSession, path: str) -> None:
    fs, where = _fs(spark, path)
    fs.delete(where, True)


def size_bytes(spark: SparkSession, path: str) -> int:
    """Bytes under path, by the file system's own summary."""
    fs, where = _fs(spark, path)
    return fs.getContentSummary(where).getLength()


def frame_bytes(df: DataFrame) -> int:
    """Bytes of the files that back a written frame."""
    return sum(size_bytes(df.sparkSession, p) for p in df.inputFiles())


@atexit.register
def _drop() -> None:
    for spark, path in _made:
        try:
            if spark.sparkContext._jsc is not None:
                delete(spark, path)
        except Exception:  # noqa: BLE001  the session may be gone by now
            return


def export_report(runs: DataFrame, path: str, form: str) -> None:
    """Measured runs as CSV with a header or as JSON lines; fails if path exists. Nested columns need JSON."""
    writer = runs.write.mode("errorifexists")
    (writer.option("header", True) if form == "csv" else writer).format(form).save(path)


def read_report(spark: SparkSession, path: str, form: str, schema: str) -> DataFrame:
    """A report with the given schema; a row that doesn't fit it raises."""
    return spark.read.format(form).schema(schema).option("header", True).option("mode", "FAILFAST").load(path)


class IndexStore:
    """Versioned index directories. A version's manifest is written last, so readers never see half of one."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")

    def versions(self, name: str) -> list[int]:
        fs, where = _fs(self.spark, f"{self.root}/{name}")
        if not fs.exists(where):
            return []
        found = [s.getPath() for s in fs.listStatus(where)]
        return sorted(int(p.getName()[1:]) for p in found if p.getName()[:1] == "v" and fs.exists(self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(p, "_manifest")))

    def save(self, name: str, tables: dict[str, DataFrame], settings: dict, partition_by: dict[str, list[str]] | None = None) -> int:
        version = max(self.versions(name), default=0) + 1
        at = f"{self.root}/{name}/v{version}"
        for key, df in tables.items():
            writer = df.write.mode("errorifexists")
            if by := (partition_by or {}).get(key):
                writer = writer.partitionBy(*by)
            writer.parquet(f"{at}/{key}")
        row = [(name, version, json.dumps(settings, sort_keys=True), sorted(tables), time.time())]
        self.spark.createDataFrame(row, "name string, version int, settings string, tables array<string>, written_at double").coalesce(1).write.mode("errorifexists").json(f"{at}/_manifest")
        return version

    def load(self, name: str, version: int | None = None) -> tuple[dict[str, DataFrame], dict]:
        version = version or max(self.versions(name))
        at = f"{self.root}/{name}/v{version}"
        fs, where = _fs(self.spark, f"{at}/_manifest")
        lines = [line for s in fs.listStatus(where) if s.getPath().getName().startswith("part-") for line in self.spark.read.text(s.getPath().toString()).collect()]
        row = json.loads(lines[0][0])
        return {k: self.spark.read.parquet(f"{at}/{k}") for k in row["tables"]}, json.loads(row["settings"])

    def bytes(self, name: str, version: int) -> int:
        return size_bytes(self.spark, f"{self.root}/{name}/v{version}")
