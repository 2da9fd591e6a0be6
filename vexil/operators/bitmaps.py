"""Inverted label bitmaps: one 32,768-bit slice per label and bucket; zero slices are absent.

Every slice is at most 4 KB, so a label over any number of rows never meets in one place.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def with_ordinals(rows: DataFrame, key: str = "id", ranges: int = 64) -> DataFrame:
    """Dense positions `ord` from 0 in order of key, without a global window.

    Split points (at most `ranges`) cut the keys; rows are numbered within a range and a range
    starts after the counts of the ranges before it.
    """
    cuts = rows.select(F.approx_percentile(key, [i / ranges for i in range(1, ranges)])).first()[0] or []
    cuts = sorted(set(cuts))
    part = F.lit(0)
    for c in cuts:
        part = part + (F.col(key) > c).cast("int")
    ranged = rows.withColumn("_part", part)
    counts = ranged.groupBy("_part").count()  # at most `ranges` rows
    before = counts.select("_part", F.coalesce(F.sum("count").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    numbered = ranged.withColumn("_row", F.row_number().over(Window.partitionBy("_part").orderBy(key)))
    return numbered.join(F.broadcast(before), "_part").withColumn("ord", F.col("_before") + F.col("_row") - 1).drop("_part", "_row", "_before")


def build_label_bitmaps(rows: DataFrame) -> DataFrame:
    """label, bucket, bm from rows with ord and labels."""
    flat = rows.select((F.col("ord") + 1).alias("o"), F.explode("labels").alias("label"))
    return flat.groupBy("label", F.bitmap_bucket_number("o").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("o")).alias("bm"))


def universe(rows: DataFrame) -> DataFrame:
    """bucket, bm with every row's bit set."""
    o = rows.select((F.col("ord") + 1).alias("o"))
    return o.groupBy(F.bitmap_bucket_number("o").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("o")).alias("bm"))


def _asked(bitmaps: DataFrame, queries: DataFrame) -> DataFrame:
    wanted = queries.select("qid", F.size("qlabels").alias("m"), F.explode("qlabels").alias("label"))
    return bitmaps.join(wanted, "label")


def bitmap_all(bitmaps: DataFrame, queries: DataFrame, everything: DataFrame | None = None) -> DataFrame:
    """qid, bucket, bm of the rows that have all asked labels; an empty set asks for everything."""
    found = _asked(bitmaps, queries).groupBy("qid", "bucket").agg(F.bitmap_and_agg("bm").alias("bm"), F.count("*").alias("k"), F.first("m").alias("m")).where("k = m").select("qid", "bucket", "bm")
    if everything is not None:
        found = found.unionByName(queries.where("size(qlabels) = 0").select("qid").join(everything))
    return found


def bitmap_any(bitmaps: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, bucket, bm of the rows that have some asked label."""
    return _asked(bitmaps, queries).groupBy("qid", "bucket").agg(F.bitmap_or_agg("bm").alias("bm"))


def bitmap_not(found: DataFrame, queries: DataFrame, everything: DataFrame) -> DataFrame:
    """The complement of found within the rows. Bytes of everything that found lacks are kept by the byte-wise rule a - (a & b)."""
    whole = queries.select("qid").join(everything).withColumnRenamed("bm", "u")
    both = whole.join(found, ["qid", "bucket"], "left")
    return both.select("qid", "bucket", _minus(F.col("u"), F.col("bm")).alias("bm"))


def _minus(a: Column, b: Column) -> Column:
    """a AND NOT b over binary slices, 8 hex digits at a time."""

    def words(x: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.lit(1023)), lambda i: F.conv(F.substr(F.hex(x), i * 8 + F.lit(1), F.lit(8)), 16, 10).cast("bigint"))

    less = F.zip_with(words(a), words(b), lambda x, y: F.lpad(F.hex(x.bitwiseAND(F.bitwise_not(y))), 8, "0"))
    return F.when(b.isNull(), a).otherwise(F.unhex(F.array_join(less, "")))


def bit_is_set(bm: Column, ord_: Column) -> Column:
    """Whether the row at position ord_ is in its bucket's slice."""
    at = F.bitmap_bit_position(ord_ + 1)
    byte = F.conv(F.hex(F.substr(bm, F.floor(at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    return F.getbit(byte.cast("bigint"), (at % 8).cast("int")) == 1


def bitmap_members(found: DataFrame, rows: DataFrame) -> DataFrame:
    """qid and the rows whose bit is set; the join is on the bucket."""
    placed = rows.withColumn("bucket", F.bitmap_bucket_number(F.col("ord") + 1))
    return found.join(placed, "bucket").where(bit_is_set(F.col("bm"), F.col("ord")))


def bitmap_equal(bitmaps: DataFrame, queries: DataFrame, rows: DataFrame, everything: DataFrame | None = None) -> DataFrame:
    """qid, bucket, bm of equal label sets: the AND map, then an exact check of the rows in it."""
    hits = bitmap_members(bitmap_all(bitmaps, queries, everything), rows).join(queries.select("qid", "qlabels"), "qid").where("labels = qlabels")
    return hits.groupBy("qid", "bucket").agg(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("ord") + 1)).alias("bm"))


def bitmap_combine(left: DataFrame, right: DataFrame, how: str) -> DataFrame:
    """Nested expressions: AND or OR of two filter maps."""
    both = left.select("qid", "bucket", "bm").unionByName(right.select("qid", "bucket", "bm"))
    if how == "or":
        return both.groupBy("qid", "bucket").agg(F.bitmap_or_agg("bm").alias("bm"))
    return both.groupBy("qid", "bucket").agg(F.bitmap_and_agg("bm").alias("bm"), F.count("*").alias("k")).where("k = 2").drop("k")


def filter_map(scenario: str, bitmaps: DataFrame, queries: DataFrame, rows: DataFrame) -> DataFrame:
    if scenario == "nofilter":
        return queries.select("qid").join(universe(rows))
    if scenario == "containment":
        return bitmap_all(bitmaps, queries, universe(rows))
    if scenario == "overlap":
        return bitmap_any(bitmaps, queries)
    if scenario in ("equality", "fixed"):
        return bitmap_equal(bitmaps, queries, rows, universe(rows))
    raise ValueError(f"no bitmap route for {scenario}")


def scan_filter_map(rows: DataFrame, queries: DataFrame, passes: Column) -> DataFrame:
    """Baseline: evaluate the predicate on every row for each query, then build the bitmap."""
    hits = rows.join(F.broadcast(queries.select("qid", "qlabels")), passes).select("qid", (F.col("ord") + 1).alias("o"))
    return hits.groupBy("qid", F.bitmap_bucket_number("o").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("o")).alias("bm"))


def cardinality(found: DataFrame) -> DataFrame:
    """qid, n: passing rows from the bitmap alone."""
    return found.groupBy("qid").agg(F.sum(F.bitmap_count("bm")).alias("n"))
