"""Operator 2: mix sources to target weights by pivotal dependent rounding.

Sources share the corpus' total size by weight; a source stops at `cap` times its own
size and what it can't take goes to the others by weight. Each document of a source
wants target / source_size copies: the whole part is taken, the fraction is rounded by
pairs. A pair moves mass (words) from one document to the other, at random and without
bias, until one of the two is integral; the sum of words never changes. Pairs form a
reduction tree: blocks of FAN documents fold to one document with a fraction left, those
fold again, until a source has one. It takes that fraction in words (`residual="words"`:
each source hits its target to the word) or is rounded at random (`"copies"`).

All steps are DataFrame functions on (doc_id, source, size); texts are never shuffled.
Draws are hashes, so reruns agree.

Cases: null text has size 0. Documents of size 0 are kept once and cost nothing. A null
source is a source of its own, the last. Where doc_ids are null or repeated, rows go by a 64-bit hash of
doc_id, source, size and a number among the rows that have these alike, counted within read partitions first, so
that no id gathers its rows. An empty table gives an empty mix.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_RE, free_names, materialise

FAN = 64


def words_in(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_RE)), F.lit(0)).cast("bigint")


def source_targets(sized: DataFrame, cycle: int = 3, cap: float = 3.0) -> DataFrame:
    """source, n_docs, source_size and target of each source; weights 1..cycle repeat by code point, null last.

    Water-filling in one pass: a source is capped if what is left per unit of weight, when all
    sources with a smaller ceiling per unit of weight have taken theirs, lies above its ceiling.
    The windows run over one row per source.
    """
    per = sized.groupBy("source").agg(F.count("*").alias("n_docs"), F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").isNull(), "source")
    ranked = per.withColumn("weight", (F.row_number().over(order) - 1) % cycle + 1).withColumn("ceiling", F.col("source_size") * cap)
    before = Window.orderBy(F.col("ceiling") / F.col("weight"), F.col("source").isNull(), "source").rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    left = F.sum("source_size").over(everything) - F.coalesce(F.sum("ceiling").over(before), F.lit(0.0))
    weight_left = F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0))
    level = ranked.withColumn("level", left / weight_left).withColumn("open", F.col("ceiling") >= F.col("level") * F.col("weight"))
    # levels grow up to the first open source and fall from there, so that one has the largest of the open ones
    final = F.max(F.when(F.col("open"), F.col("level"))).over(everything)
    return level.select("source", "n_docs", "source_size", F.least(F.col("ceiling"), final * F.col("weight")).cast("double").alias("target"))


def _draw(*parts: Column) -> Column:
    return F.pmod(F.xxhash64(*parts), F.lit(1 << 53)).cast("double") / float(1 << 53)


_ITEM = "struct<key:bigint,mass:double,size:double>"
_DONE = "struct<key:bigint,up:int>"


def _fold(items: Column, seed: int) -> Column:
    """Pair the items of a block one after the other; struct(rest item or null, done)."""

    def item(x: Column, mass: Column) -> Column:
        return F.struct(x["key"].alias("key"), mass.alias("mass"), x["size"].alias("size"))

    def done(x: Column, up: int) -> Column:
        return F.array(F.struct(x["key"].alias("key"), F.lit(up).alias("up")))

    def state(rest: Column, out: Column) -> Column:
        return F.struct(rest.cast(_ITEM).alias("rest"), out.cast(f"array<{_DONE}>").alias("done"))

    nobody = F.lit(None).cast(_ITEM)

    def pair(acc: Column, x: Column) -> Column:
        r, out = acc["rest"], acc["done"]
        to_r, to_x = F.least(r["size"] - r["mass"], x["mass"]), F.least(r["mass"], x["size"] - x["mass"])
        r_gains = _draw(r["key"], x["key"], F.lit(seed)) * (to_r + to_x) < to_x
        r_room, x_room = r["size"] - r["mass"], x["size"] - x["mass"]
        return (
            F.when(r.isNull(), state(x, out))
            .when(r_gains & (r_room == x["mass"]), state(nobody, F.concat(out, done(r, 1), done(x, 0))))
            .when(r_gains & (r_room < x["mass"]), state(item(x, x["mass"] - r_room), F.concat(out, done(r, 1))))
            .when(r_gains, state(item(r, r["mass"] + x["mass"]), F.concat(out, done(x, 0))))
            .when(x_room == r["mass"], state(nobody, F.concat(out, done(x, 1), done(r, 0))))
            .when(x_room < r["mass"], state(item(r, r["mass"] - x_room), F.concat(out, done(x, 1))))
            .otherwise(state(item(x, x["mass"] + r["mass"]), F.concat(out, done(r, 0))))
        )

    return F.aggregate(items, state(nobody, F.array()), pair)


def unique_ids(docs: DataFrame) -> bool:
    """Whether doc_id is neither null nor repeated."""
    return not docs.where("doc_id is null").limit(1).count() and not docs.groupBy("doc_id").count().where("count > 1").limit(1).count()


def row_keys(rows: DataFrame, key: str, size: Column) -> DataFrame:
    """rows with a bigint column `key` that tells them apart; the keys don't depend on how rows are dealt out."""
    if unique_ids(rows):
        return rows.withColumn(key, F.col("doc_id").cast("bigint"))
    part, alike, number, held, before = free_names(["_part", "_alike", "_number", "_held", "_before"], [*rows.columns, key])
    kind = F.xxhash64("doc_id", F.col("doc_id").isNull(), "source", F.col("source").isNull(), size)
    placed = materialise(rows.withColumn(part, F.spark_partition_id()).withColumn(alike, kind), "placed")
    counts = placed.groupBy(alike, part).agg(F.count("*").alias(held))
    earlier = Window.partitionBy(alike).orderBy(part).rowsBetween(Window.unboundedPreceding, -1)  # a row for each read partition
    counts = counts.withColumn(before, F.coalesce(F.sum(held).over(earlier), F.lit(0))).drop(held)
    numbered = placed.withColumn(number, F.row_number().over(Window.partitionBy(alike, part).orderBy(part)))
    return numbered.join(counts, [alike, part]).withColumn(key, F.xxhash64(alike, F.col(number) + F.col(before))).select(*rows.columns, key)


def mix(docs: DataFrame, residual: str = "words", cycle: int = 3, cap: float = 3.0, seed: int = 7, size: Column | None = None, key: str | None = None) -> DataFrame:
    """doc_id, key, size, source, source_size, target, copies, extra, taken of every document.

    copies counts whole copies, extra the words of one more, partial copy; taken is their sum in
    words. key tells rows apart: the column named so, else that of row_keys.
    """
    sized = materialise(docs.select("doc_id", "source", (words_in(F.col("text")) if size is None else size).alias("size"), *([F.col(key).cast("bigint").alias("key")] if key else [])), "sizes")
    if not key:
        sized = materialise(row_keys(sized, "key", F.col("size")), "sizes")
    targets = materialise(source_targets(sized, cycle, cap), "targets")
    most = targets.agg(F.max("n_docs")).first()[0] or 0
    joined = sized.join(targets, sized.source.eqNullSafe(targets.source)).drop(targets.source)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    joined = joined.withColumn("rate", F.when(F.col("size") > 0, rate).otherwise(F.lit(1.0))).withColumn("whole", F.floor("rate").cast("int"))
    part = (F.col("rate") - F.col("whole")) * F.col("size")
    blocks = F.greatest(F.lit(1), F.ceil(F.col("n_docs") / FAN)).cast("bigint")
    items = joined.where((F.col("rate") > F.col("whole")) & (F.col("size") > 0)).select(
        "source", F.pmod(F.xxhash64("key", F.lit(seed)), blocks).alias("block"), blocks.alias("blocks"),
        F.struct("key", part.alias("mass"), F.col("size").cast("double").alias("size")).alias("item"),
    )
    settled = []
    for level in range(max(1, math.ceil(math.log(max(2, most), FAN)) + 1)):
        gathered = items.groupBy("source", "block", "blocks").agg(F.array_sort(F.collect_list("item")).alias("items"))
        folded = materialise(gathered.select("source", "block", "blocks", _fold(F.col("items"), seed + level).alias("f")), f"fold{level}")
        settled.append(folded.select(F.explode("f.done").alias("d")).select("d.key", F.col("d.up").alias("up"), F.lit(0.0).alias("rest")))
        fewer = F.greatest(F.lit(1), F.ceil(F.col("blocks") / FAN)).cast("bigint")
        items = folded.where("f.rest is not null").select("source", F.pmod("block", fewer).alias("block"), fewer.alias("blocks"), F.col("f.rest").alias("item"))
    if residual == "words":
        last = items.select("item.key", F.lit(0).alias("up"), F.col("item.mass").alias("rest"))
    else:
        last = items.select("item.key", (_draw(F.col("item.key"), F.lit(seed - 1)) * F.col("item.size") < F.col("item.mass")).cast("int").alias("up"), F.lit(0.0).alias("rest"))
    for s in settled:
        last = last.unionByName(s)
    out = joined.join(last, "key", "left")
    copies = (F.col("whole") + F.coalesce("up", F.lit(0))).cast("int")
    extra = F.least(F.round(F.coalesce("rest", F.lit(0.0))).cast("bigint"), F.col("size"))
    return out.select("doc_id", "key", "size", "source", "source_size", "target", copies.alias("copies"), extra.alias("extra"), (copies * F.col("size") + extra).cast("bigint").alias("taken"))
