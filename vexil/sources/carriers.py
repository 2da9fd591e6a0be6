"""Base datasets (id, vec, labels) and queries (qid, qvec, qlabels) derived from the given tables.

"""

from __future__ import annotations

import string
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

from .store import written, written_in_slices

CARRIERS = ("emb_zipf", "emb_single", "emb_fixed4", "doc_attr", "doc_fixed4", "basket_nation", "basket_type", "basket_fixed4", "page_terms")

# Attribute codes and types of the given tables.
LANGUAGES = ["en", "fr", "de", "es"]
PART_TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
SLICE_ORDERS, MOST_SLICES = 2_500_000, 4  # orders of one slice of a derived base, and how often the lines are read for it at most
FLAGS = ["AF", "AO", "NF", "NO", "RF", "RO"]
FIXED_MULTIPLIERS = [(7919, 1009), (104729, 1013), (1299709, 1019), (15485863, 1021)]


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def normalize_labels(labels: Column) -> Column:
    """Canonical label set: sorted, distinct, without nulls; null becomes empty."""
    return F.array_sort(F.array_distinct(F.array_compact(F.coalesce(labels, F.array().cast("array<int>")))))


def _zipf(vec_id: Column) -> Column:
    return F.filter(F.sequence(F.lit(1), F.lit(24)), lambda j: ((vec_id + 1) * (7919 + 1300 * j) + j * 104729) % 9973 < F.floor(F.lit(9973) / (j + 2)))


def _fixed4(key: Column) -> Column:
    return F.array(*(((key * m % p) % 3 + 3 * i).cast("int") for i, (m, p) in enumerate(FIXED_MULTIPLIERS)))


def _letter_shares(text: pd.Series) -> pd.Series:
    out = []
    for t in text:
        n = np.bincount(np.frombuffer((t or "").encode().lower(), np.uint8), minlength=123)[97:123].astype(float)
        out.append(n / max(n.sum(), 1.0))
    return pd.Series(out)


def letter_profile(text: Column) -> Column:
    """Share of each letter a-z among the letters of text; zeros without letters. One pass over the bytes
    in an Arrow batch, where 26 passes of string functions would dominate every query on texts."""
    return F.pandas_udf(_letter_shares, ArrayType(DoubleType()))(text)  # made here: importing needs no session


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = read(spark, sf_dir, "labels")
    return read(spark, sf_dir, "documents").join(labels, "doc_id", "left")


def _doc_labels() -> Column:
    lang = F.array_position(F.array(*map(F.lit, LANGUAGES)), F.col("lang")).cast("int")
    source = F.try_add(F.lit(10), F.regexp_extract("source", r"(\d+)$", 1).try_cast("int"))
    size = F.when(F.col("n_chars") < 1000, 40).when(F.col("n_chars") < 4000, 41).otherwise(42)
    return normalize_labels(F.array(F.when(lang > 0, lang), source, F.when(F.col("quality") == 1, 30).when(F.col("quality") == 0, 31), F.when(F.col("toxic") == 1, 32), size))


def order_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per order: 16 numbers, and the sets of supplier nations and part types (as bits in the sums, which stay a hash aggregation; a type that isn't listed is "")."""
    part = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_type", "p_size")
    supplier = read(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity", "l_discount", "l_tax", "l_returnflag", "l_linestatus").join(part, "l_partkey").join(supplier, "l_suppkey")
    quantity, flag = F.col("l_quantity").cast("bigint"), F.concat("l_returnflag", "l_linestatus")
    kind = F.when(F.col("p_type").isNotNull(), F.coalesce(*(F.when(F.col("p_type") == t, 1 << i) for i, t in enumerate(PART_TYPES)), F.lit(1 << len(PART_TYPES))))
    sums = lines.groupBy("l_orderkey").agg(
        *(F.sum(F.when(F.col("p_type") == t, quantity).otherwise(0)).alias(f"t{i}") for i, t in enumerate(PART_TYPES)), *(F.sum(F.when(flag == f, quantity).otherwise(0)).alias(f"f{i}") for i, f in enumerate(FLAGS)),
        F.sum(quantity).alias("qty"), F.sum(F.round(F.col("l_discount") * 100).cast("bigint")).alias("disc"), F.sum(F.round(F.col("l_tax") * 100).cast("bigint")).alias("tax"), F.sum(F.col("p_size").cast("bigint")).alias("size"), F.count("*").alias("n"),
        F.collect_set(F.col("s_nationkey").cast("int")).alias("nations"), F.bit_or(kind).alias("kinds"),
    )
    types = F.array_compact(F.array(*(F.when(F.col("kinds").bitwiseAND(1 << i) > 0, t) for i, t in enumerate([*PART_TYPES, ""]))))
    orders = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_totalprice", "o_orderdate")
    d = lambda c: F.col(c).cast("double")
    vec = F.array(*(d(f"t{i}") / d("qty") for i in range(6)), *(d(f"f{i}") / d("qty") for i in range(6)), d("disc") / (d("n") * 100), d("tax") / (d("n") * 100), F.round(F.log1p("o_totalprice"), 6) / 14, d("size") / (d("n") * 50))
    return sums.join(orders, "l_orderkey").select(F.col("l_orderkey").alias("id"), vec.alias("vec"), "nations", types.alias("types"), F.col("o_orderdate").alias("attr"))


def page_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, host, language code from the path, and the tag-stripped text."""
    text = F.regexp_replace("html", r"<[^>]*>", "")
    return read(spark, sf_dir, "pages").select(
        F.col("page_id").alias("id"), F.regexp_extract("url", r"://([^/?#]*)", 1).alias("host"), F.array_position(F.array(*map(F.lit, LANGUAGES)), F.regexp_extract("url", r"://[^/?#]*/(en|fr|de|es)/", 1)).cast("int").alias("code"), text.alias("shown")
    )


def carrier(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """id, vec (array<double>), labels and held (True for the rows set aside as queries)."""
    key = F.col("id")
    if name.startswith("emb"):
        base = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), "label")
        labels = {"emb_zipf": _zipf(key), "emb_single": F.array("label"), "emb_fixed4": _fixed4(key)}[name]
        held = key % 10 == 3
    elif name.startswith("doc"):
        base = _documents(spark, sf_dir).withColumnRenamed("doc_id", "id").withColumn("vec", letter_profile(F.col("text")))
        labels, held = (_doc_labels() if name == "doc_attr" else _fixed4(key)), key * 7919 % 1009 < 100
    elif name.startswith("basket"):
        base = order_profile(spark, sf_dir)
        labels = {"basket_nation": F.col("nations"), "basket_type": F.transform("types", lambda t: F.array_position(F.array(*map(F.lit, PART_TYPES)), t).cast("int")), "basket_fixed4": _fixed4(key)}[name]
        held = key * 7919 % 1009 < 20
    elif name == "page_terms":
        pages = page_parts(spark, sf_dir)
        hosts = label_dictionary(pages, ["host"]).select(F.col("value").alias("host"), F.col("label").alias("host_label"))
        base = pages.join(hosts, "host", "left").withColumn("vec", letter_profile(F.col("shown")))
        size = F.when(F.length("shown") < 1000, 6).when(F.length("shown") < 4000, 7).otherwise(8)
        labels, held = F.array(F.when(F.col("code") > 0, F.col("code")), size, F.col("host_label") + 10), key * 7919 % 1009 < 100
    else:
        raise ValueError(f"no carrier {name}")
    return base.select("id", "vec", normalize_labels(labels.cast("array<int>")).alias("labels"), F.coalesce(held, F.lit(False)).alias("held"))


def label_dictionary(df: DataFrame, attributes: list[str], ranges: int | None = None) -> DataFrame:
    """attr, value, label: dense codes from 1 for the distinct values, in order of attribute and value.

    Values are dealt to ranges (as many as the session's shuffle partitions, if not given) and numbered within a range; a range starts after the counts of those before it,
    so an attribute with many values never meets in one task.
    """
    pairs = df.select(F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value")) for a in attributes))).alias("p")).select("p.*").where("value is not null").distinct()
    ranged = written(pairs.repartitionByRange(*([ranges] if ranges else []), "attr", "value").withColumn("part", F.spark_partition_id()), "dictionary")
    counts = ranged.groupBy("part").count()  # a row for each range
    before = counts.select("part", F.coalesce(F.sum("count").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("off"))
    numbered = ranged.withColumn("r", F.row_number().over(Window.partitionBy("part").orderBy("attr", "value")))
    return numbered.join(F.broadcast(before), "part").select("attr", "value", (F.col("r") + F.col("off")).cast("int").alias("label"))


def vector_fault(vec: Column, dims: int) -> Column:
    """Why a vector can't take part in a search: null, length, not finite; else none."""
    bad = F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.when(vec.isNull(), "null").when(F.size(vec) != dims, "length").when(bad, "not finite").otherwise("none")


def assert_vectors(base: DataFrame) -> int | None:
    """The dimensions that all vectors share (None: no rows), in one pass; raises on nulls, other lengths and components that aren't finite."""
    size, bad = F.size("vec"), F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    low, high, faults = base.agg(F.min(size), F.max(size), F.count_if(F.col("vec").isNull() | bad)).first()
    if faults or low != high:
        raise ValueError(f"{faults} vectors are null or not finite; dimensions run from {low} to {high}")
    return low


@dataclass
class Dataset:
    base: DataFrame  # id, vec, labels
    queries: DataFrame  # qid, qvec, qlabels
    rows: DataFrame  # id, vec, labels of the base and the rows set aside


def asked_labels(key: Column, labels: Column, width: int) -> Column:
    """`width` of a row's labels, in an order drawn per row and label, so that a label is asked for as often as rows have it."""
    drawn = F.array_sort(F.transform(labels, lambda x: F.struct((((key + 3) * (x * 1409 + 5003) + x * x * 31) % 10007).alias("h"), x.alias("x"))))
    return F.array_sort(F.transform(F.slice(drawn, 1, width), lambda s: s["x"]))


def dataset(spark: SparkSession, sf_dir: str, name: str, width: int | None = 1, limit: int | None = None) -> Dataset:
    """Base rows and the queries, all held rows with labels enough unless a limit is given; a query asks for `width` labels of its own row (None: all)."""
    rows = carrier(spark, sf_dir, name)
    asked = F.col("labels") if width is None else asked_labels(F.col("id"), F.col("labels"), width)
    long_enough = F.size("labels") >= (1 if width is None else width)
    queries = rows.where("held").where(long_enough).select(F.col("id").alias("qid"), F.col("vec").alias("qvec"), asked.alias("qlabels"))
    return Dataset(rows.where("not held").select("id", "vec", "labels"), queries if limit is None else queries.orderBy("qid").limit(limit), rows.select("id", "vec", "labels"))


def derived(spark: SparkSession, sf_dir: str, name: str, d: Dataset) -> Dataset:
    """d with base and queries written once. Profiles of many orders are written in slices: the shuffle of one is on disk at a time."""
    slices = min(MOST_SLICES, -(-read(spark, sf_dir, "orders").count() // SLICE_ORDERS)) if name.startswith("basket") else 1
    return Dataset(written_in_slices(d.base, "base", "id", max(1, slices)), written(d.queries, "queries"), d.rows)


# ------------------------------------------------------------------ the same in SQL


def _sql_labels(name: str) -> str:
    fixed = "[" + ", ".join(f"(id*{m} % {p}) % 3 + {3 * i}" for i, (m, p) in enumerate(FIXED_MULTIPLIERS)) + "]"
    return {"emb_zipf": "list_filter(range(1,25), lambda j: ((id+1)*(7919+1300*j)+j*104729) % 9973 < 9973 // (j+2))", "emb_single": "[label]"}.get(name, fixed)


def carrier_sql(name: str, width: int | None = 1, limit: int | None = None) -> str:
    """CTEs rows_ and base(id, vec, labels) and queries(qid, qvec, qlabels), to stand after WITH."""
    if name.startswith("emb"):
        rows = f"select id, vec, {_sql_labels(name)} as labels, id % 10 = 3 as held from (select vec_id as id, embedding::double[] as vec, label from embeddings)"
    elif name.startswith("doc"):
        low = "translate(coalesce(text,''), '" + string.ascii_uppercase + "', '" + string.ascii_lowercase + "')"
        counts = "[" + ", ".join(f"(length(low)-length(replace(low,'{c}','')))::double" for c in string.ascii_lowercase) + "]"
        code = "list_position(['" + "','".join(LANGUAGES) + "'], lang)"
        attrs = f"list_sort(list_distinct(list_filter([case when {code} > 0 then {code} end, 10 + try_cast(regexp_extract(source,'(\\d+)$',1) as int), case quality when 1 then 30 when 0 then 31 end, case toxic when 1 then 32 end, case when n_chars < 1000 then 40 when n_chars < 4000 then 41 else 42 end], lambda x: x is not null)))"
        labels = attrs if name == "doc_attr" else _sql_labels("fixed")
        rows = f"select id, list_transform(c, lambda x: x / greatest(list_sum(c), 1.0)) as vec, {labels} as labels, coalesce(id*7919 % 1009 < 100, false) as held from (select *, {counts} as c from (select doc_id as id, {low} as low, lang, source, n_chars, quality, toxic from documents left join labels using (doc_id)))"
    elif name == "page_terms":
        counts = "[" + ", ".join(f"(length(low)-length(replace(low,'{c}','')))::double" for c in string.ascii_lowercase) + "]"
        parts = r"select page_id as id, regexp_extract(url, '://([^/?#]*)', 1) as host, regexp_extract(url, '://[^/?#]*/(en|fr|de|es)/', 1) as lang, regexp_replace(html, '<[^>]*>', '', 'g') as shown from pages"
        hosts = f"select host, row_number() over (order by host) as code from (select distinct host from ({parts}) where host is not null)"
        code = "list_position(['" + "','".join(LANGUAGES) + "'], lang)"
        labels = f"list_sort(list_distinct(list_filter([case when {code} > 0 then {code} end, case when length(shown) < 1000 then 6 when length(shown) < 4000 then 7 else 8 end, code + 10], lambda x: x is not null)))"
        low = "translate(coalesce(shown,''), '" + string.ascii_uppercase + "', '" + string.ascii_lowercase + "')"
        rows = f"select id, list_transform(c, lambda x: x / greatest(list_sum(c), 1.0)) as vec, {labels} as labels, coalesce(id*7919 % 1009 < 100, false) as held from (select *, {counts} as c from (select *, {low} as low from ({parts}) left join ({hosts}) using (host)))"
    else:
        nums = ", ".join([*(f"sum(case when p_type='{t}' then l_quantity::bigint else 0 end) t{i}" for i, t in enumerate(PART_TYPES)), *(f"sum(case when l_returnflag||l_linestatus='{f}' then l_quantity::bigint else 0 end) f{i}" for i, f in enumerate(FLAGS))])
        vec = "[" + ", ".join([*(f"t{i}::double/qty::double" for i in range(6)), *(f"f{i}::double/qty::double" for i in range(6)), "disc::double/(n*100)", "tax::double/(n*100)", "round(ln(1+o_totalprice),6)/14", "size::double/(n*50)"]) + "]"
        types = "[" + ",".join(f"'{t}'" for t in PART_TYPES) + "]"
        labels = {"basket_nation": "list_sort(nations)", "basket_type": f"list_sort(list_transform(types, lambda t: list_position({types}, t)))"}.get(name, _sql_labels("fixed"))
        rows = f"select id, {vec} as vec, {labels} as labels, id*7919 % 1009 < 20 as held from (select l_orderkey as id, {nums}, sum(l_quantity::bigint) qty, sum(round(l_discount*100)::bigint) disc, sum(round(l_tax*100)::bigint) tax, sum(p_size::bigint) size, count(*) n, list(distinct s_nationkey::int) nations, list(distinct p_type) types from lineitem join part on p_partkey=l_partkey join supplier on s_suppkey=l_suppkey group by 1) join orders on o_orderkey=id"
    asked = "labels"
    if width is not None:
        drawn = "list_sort(list_transform(labels, lambda x: {'h': ((id + 3) * (x * 1409 + 5003) + x * x * 31) % 10007, 'x': x}))"
        asked = f"list_sort(list_transform(({drawn})[1:{width}], lambda s: s.x))"
    return f"rows_ as materialized ({rows}), base as materialized (select id, vec, labels from rows_ where not held), queries as materialized (select id as qid, vec as qvec, {asked} as qlabels from rows_ where held and len(labels) >= {1 if width is None else width}{"" if limit is None else f" order by id limit {limit}"})"
