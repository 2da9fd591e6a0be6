"""Change streams over label sets, windows over events, and the update path of an index.

Events become changes: purchase and signup add their label, error drops it, the others replace the set. The label of
an event type is its place in EVENT_LABELS. `ts` is cast to TIMESTAMP because a watermark needs it.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

# Labels of event types from 1, and what an event does.
EVENT_LABELS = ["view", "click", "error", "purchase", "signup"]
OPERATIONS = {"purchase": "add", "signup": "add", "error": "drop"}


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/events.parquet")


def changes(rows: DataFrame) -> DataFrame:
    """id, op, label, ts, event_id of each event."""
    op = F.coalesce(F.create_map(*(F.lit(x) for kv in OPERATIONS.items() for x in kv))[F.col("event_type")], F.lit("put"))
    label = F.array_position(F.array(*map(F.lit, EVENT_LABELS)), F.col("event_type")).cast("int")
    return rows.select(F.col("user_id").alias("id"), op.alias("op"), label.alias("label"), F.col("ts").cast("timestamp").alias("ts"), "event_id")


def _apply(state: Column, change: Column) -> Column:
    return (
        F.when(change["op"] == "put", F.array(change["label"]))
        .when(change["op"] == "drop", F.array_remove(state, change["label"]))
        .otherwise(F.array_sort(F.array_union(state, F.array(change["label"]))))
    )


def current_labels(log: DataFrame) -> DataFrame:
    """id, labels after all changes. Only what follows an entity's last put is folded, so hot entities stay small."""
    last = log.where("op = 'put'").groupBy("id").agg(F.max(F.struct("ts", "event_id")).alias("p"))
    tail = log.join(last, "id", "left").where("p is null or struct(ts, event_id) >= p")
    ordered = tail.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "op", "label"))).alias("log"))
    return ordered.select("id", F.aggregate("log", F.array().cast("array<int>"), _apply).alias("labels"))


def replay_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = current_labels(changes(events(spark, sf_dir)))
    return found.select("id", F.array_join("labels", ",").alias("labels"))


_CHANGES_SQL = "log as (select user_id as id, event_id, ts, case event_type when 'purchase' then 'add' when 'signup' then 'add' when 'error' then 'drop' else 'put' end as op, list_position(['" + "','".join(EVENT_LABELS) + "'], event_type) as label from events)"
# after the last put a label is in if its own last change is no drop
REPLAY_SQL = f"""with {_CHANGES_SQL}, p as (select id, max(struct_pack(ts, event_id)) as p from log where op = 'put' group by 1),
tail as (select log.* from log left join p using (id) where p is null or struct_pack(ts, event_id) >= p),
last as (select id, label, arg_max(op, struct_pack(ts, event_id)) as op from tail group by all)
select id, coalesce(string_agg(label::varchar, ',' order by label) filter (op <> 'drop'), '') as labels from last group by 1"""


def asof_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For every purchase, the user's last event before it: the version that was valid then."""
    rows = events(spark, sf_dir)
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    versions = rows.withColumn("valid", F.last(F.struct("event_id", "event_type")).over(before))
    return versions.where("event_type = 'purchase'").select("event_id", F.col("valid.event_id").alias("version"), F.col("valid.event_type").alias("label"))


ASOF_SQL = "select event_id, version, label from (select event_id, event_type, lag(event_id) over w as version, lag(event_type) over w as label from events window w as (partition by user_id order by ts, event_id)) where event_type = 'purchase'"


def _times(found: DataFrame) -> DataFrame:
    return found.select(F.unix_timestamp(F.col("window.start").cast("timestamp")).alias("start_s"), *[c for c in found.columns if c != "window"])


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _times(changes(events(spark, sf_dir)).groupBy(F.window("ts", "1 hour"), "label").agg(F.count("*").alias("n")))


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _times(changes(events(spark, sf_dir)).groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count("*").alias("n")))


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = changes(events(spark, sf_dir)).groupBy(F.session_window("ts", "15 minutes").alias("window"), "id").agg(F.count("*").alias("n"))
    return _times(found).select("id", "start_s", "n")


_LABEL = "list_position(['" + "','".join(EVENT_LABELS) + "'], event_type)"
TUMBLING_SQL = f"select (epoch_us(ts) // 3600000000 * 3600)::bigint as start_s, {_LABEL} as label, count(*) as n from events group by all"
SLIDING_SQL = "select (epoch_us(ts) // 1800000000 * 1800 - 1800 * o)::bigint as start_s, count(*) as n from events, (select unnest([0, 1]) as o) group by 1"
SESSION_SQL = "with g as (select *, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts) <= 900000000 then 0 else 1 end as new from events), s as (select *, sum(new) over (partition by user_id order by ts, event_id) as s from g) select user_id as id, (epoch_us(min(ts)) // 1000000)::bigint as start_s, count(*) as n from s group by user_id, s"


# ------------------------------------------------------------------ streams


def change_stream(spark: SparkSession, folder: str, schema, delay: str = "10 minutes") -> DataFrame:
    """Changes read from files of events as they come, with a watermark and without repeated events."""
    rows = changes(spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder))
    return rows.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def label_frequency_stream(stream: DataFrame) -> DataFrame:
    return stream.groupBy(F.window("ts", "1 hour"), "label").count()


def _fold(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    labels = set(state.get[0]) if state.exists else set()
    rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
    for op, label in zip(rows["op"], rows["label"]):
        if op == "put":
            labels = {int(label)}
        elif op == "drop":
            labels.discard(int(label))
        else:
            labels.add(int(label))
    state.update((sorted(labels),))
    yield pd.DataFrame({"id": [key[0]], "labels": [sorted(labels)]})


def stateful_labels(stream: DataFrame) -> DataFrame:
    """id, labels, updated with each micro-batch; state is one label set per entity."""
    return stream.groupBy("id").applyInPandasWithState(_fold, "id bigint, labels array<int>", "labels array<int>", "update", GroupStateTimeout.NoTimeout)


def query_stream(queries: DataFrame, answer: Callable[[DataFrame], DataFrame], path: str, checkpoint: str) -> StreamingQuery:
    """Each micro-batch of queries is answered by the batch search and appended under path."""
    return queries.writeStream.foreachBatch(lambda batch, number: answer(batch).withColumn("batch", F.lit(number)).write.mode("append").parquet(path)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def feedback_join(queries: DataFrame, feedback: DataFrame, within: str = "10 minutes") -> DataFrame:
    """Stream-stream interval join: feedback (fid, fqid, fts) that follows its query (qid, ts) within the interval."""
    q, f = queries.withWatermark("ts", within), feedback.withWatermark("fts", within)
    return q.join(f, F.expr(f"qid = fqid and fts >= ts and fts <= ts + interval {within}"))


# ------------------------------------------------------------------ updates of an index


def apply_delta(base: DataFrame, upserts: DataFrame, deletes: DataFrame) -> DataFrame:
    """base with rows replaced or added (same columns) and ids of deletes gone: one anti-join, one union."""
    gone = upserts.select("id").unionByName(deletes.select("id")).distinct()
    return base.join(gone, "id", "left_anti").unionByName(upserts.join(deletes.select("id"), "id", "left_anti").select(*base.columns))


def relabel(nodes: DataFrame, labels: DataFrame) -> DataFrame:
    """A label-free graph's nodes with new label sets (id, labels): vectors and edges stay, no rebuild."""
    new = labels.withColumnRenamed("labels", "_new")
    joined = nodes.join(new, "id", "left").withColumn("labels", F.coalesce("_new", "labels"))
    return joined.select(*nodes.columns)
