"""Graph indexes on Spark: shards built and searched in parallel, results merged by exact distance.

An index is one table of nodes (shard, id, vec, labels, level, nbrs); a traversal lives within one shard,
so a query block is sent to the shards it is routed to and one shuffle merges the answers. Shards are hashes of
the id (`hash`, every shard is asked) or coarse clusters (`centroid`, the `probe_shards` nearest are asked).
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import Constraint, constraint
from ..sources.store import written
from . import ivf, kernels, walks
from .exact import block_search, rerank, small
from .kernels import Shard

NODES = "shard bigint, id bigint, vec array<double>, labels array<int>, level int, nbrs array<array<bigint>>"
FOUND = "qid bigint, shard bigint, id bigint, dist double, dist_comps bigint, hops bigint, label_checks bigint, rounds bigint"

# Rows that one Python worker builds and walks in memory, and queries that it answers in one go.
SHARD_ROWS = 50_000
LANE_QUERIES = 10_000
LANE_LEAST = 500  # fewer queries are not worth a copy of the shard, even if cores are idle

# Build parameters of each method (tunable ones only, as many as the reference counts) and their defaults.
DEFAULTS: dict[str, dict[str, float]] = {
    "dense": {"degree": 12, "gamma": 3, "keep": 8},
    "twohop": {"degree": 12, "breadth": 24},
    "lattice": {"degree": 8, "breadth": 24, "alpha": 1.2, "cross": 3},
    "postfilter": {"degree": 12, "breadth": 32},
    "shared": {"degree": 12, "breadth": 24, "alpha": 1.2},
    "stitched": {"sub_degree": 10, "breadth": 24, "stitched_degree": 24, "alpha": 1.2},
    "fused": {"k0": 12, "pool": 24, "iters": 4, "sample": 10, "rev_sample": 10, "degree": 12, "diverse_pool": 24, "diverse_angle": 40.0, "label_weight": 2.0},
}


@dataclass
class GraphIndex:
    method: str
    nodes: DataFrame
    params: dict
    shards: int
    centroids: DataFrame | None = None
    options: dict = field(default_factory=dict)


def _build(method: str, p: dict, options: dict, frame: pd.DataFrame) -> pd.DataFrame:
    frame = frame.sort_values("id")
    x, ids = np.stack(frame["vec"].to_numpy()).astype(float), frame["id"].to_numpy()
    labels = [tuple(int(a) for a in own) for own in frame["labels"]]
    level, n = np.zeros(len(ids), int), {k: int(v) for k, v in p.items()}
    if method in ("postfilter", "twohop"):
        level, nbrs = kernels.layered(x, ids, n["degree"], n["breadth"], 1.0 if method == "postfilter" else None)
    elif method == "dense":
        level, nbrs = kernels.dense(x, ids, n["degree"], n["gamma"], n["keep"], 0)
    elif method == "lattice":
        nbrs = kernels.lattice(x, labels, n["degree"], n["breadth"], p["alpha"], n["cross"])
    elif method == "fused":
        nbrs = kernels.fused(x, labels, n["k0"], n["pool"], n["iters"], n["sample"], n["rev_sample"], n["degree"], n["diverse_pool"], p["diverse_angle"], p["label_weight"], options.get("additive", False), options.get("start", "descent"))
    else:
        members = Shard(ids, x, labels, level, [[] for _ in ids]).members
        if method == "shared":
            nbrs = kernels.shared_label(x, labels, members, n["degree"], n["breadth"], p["alpha"])
        else:
            nbrs = kernels.stitched(x, labels, members, n["sub_degree"], n["breadth"], n["stitched_degree"], p["alpha"])
    return pd.DataFrame({"shard": frame["shard"].to_numpy(), "id": ids, "vec": list(x), "labels": [list(a) for a in labels], "level": level.astype(np.int32), "nbrs": [[ids[c].tolist() for c in own] for own in nbrs]})


def fit(base: DataFrame, method: str, params: dict | None = None, shards: int | None = None, shard_by: str = "hash", options: dict | None = None) -> GraphIndex:
    """Build one graph per shard. Rows of a shard have to fit one Python worker: without a number, shards hold about SHARD_ROWS rows each (4 at least)."""
    shards = shards or max(4, -(-base.count() // SHARD_ROWS))
    p, options = DEFAULTS[method] | (params or {}), options or {}
    rows, centroids = base.select("id", "vec", "labels"), None
    if shard_by == "centroid":
        centroids = written(ivf.kmeans_centroids(base, shards), "shards")
        placed = ivf.assign(rows, centroids).withColumnRenamed("list_id", "shard")
    else:
        placed = rows.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)))

    def build(frame: pd.DataFrame) -> pd.DataFrame:
        return _build(method, p, options, frame)

    nodes = placed.groupBy("shard").applyInPandas(build, NODES)
    return GraphIndex(method, written(nodes, f"graph-{method}"), p, shards, centroids, options)


def _shard(frame: pd.DataFrame) -> Shard:
    frame = frame.sort_values("id")
    ids = frame["id"].to_numpy()
    nbrs = [[np.searchsorted(ids, np.asarray(c, np.int64)) for c in own] for own in frame["nbrs"]]
    return Shard(ids, np.stack(frame["vec"].to_numpy()).astype(float), [tuple(int(a) for a in own) for own in frame["labels"]], frame["level"].to_numpy(), nbrs)


def _search(method: str, p: dict, scenario: str, k: int, s: dict, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
    out: dict[str, list] = {c.split()[0]: [] for c in FOUND.split(", ")}
    if len(left) and len(right):
        shard = _shard(left)
        breadth = max(k, int(s.get("breadth") or len(shard.ids)))
        given = [] if right["allowed"].isna().all() else right["allowed"].tolist()
        step = max(1, min(walks.TOGETHER, walks.SEEN // len(shard.ids)) if given else walks.TOGETHER)  # given maps are one a query
        for lo in range(0, len(right), step):
            some = right.iloc[lo : lo + step]
            asked = [tuple(int(a) for a in own) for own in some["qlabels"]]
            answers = walks.search(method, p, shard, scenario, np.stack(some["qvec"].to_numpy()).astype(float), asked, given[lo : lo + step] or None, k, breadth, s)
            for qid, found, cost in zip(some["qid"], *answers):
                found = found[:k] or [(None, None)]
                for d, i in found:
                    out["qid"].append(qid)
                    out["shard"].append(int(left["shard"].iloc[0]))
                    out["id"].append(None if i is None else int(shard.ids[i]))
                    out["dist"].append(d)
                    for name in ("dist_comps", "hops", "label_checks", "rounds"):
                        out[name].append(getattr(cost, name))
    frame = pd.DataFrame(out)
    return frame.astype({"id": "Int64", "qid": "int64"}) if len(frame) else frame


def lanes_for(queries: int, shards: int, cores: int) -> int:
    """Lanes of LANE_QUERIES queries at most; more of them only where shards are so few that cores would idle."""
    return max(1, -(-queries // LANE_QUERIES), min(queries // LANE_LEAST, -(-3 * cores // shards)))


def raw_search(index: GraphIndex, queries: DataFrame, of: str | Constraint, k: int, base: DataFrame | None = None, probe_shards: int | None = None, lanes: int | None = None, **settings) -> DataFrame:
    """FOUND rows of every shard that a query visits; id is null where a shard has nothing. A shard's queries are dealt
    to `lanes` tasks (without a number, of about LANE_QUERIES each, or as many as keep the cores busy), each with its copy of the shard."""
    want = constraint(of)
    shards = index.nodes.select(F.col("shard").alias("visit")).distinct()  # a row for each shard
    asked = queries.select("qid", "qvec", "qlabels")
    if index.centroids is not None and probe_shards:
        visits = ivf.route(asked, index.centroids, probe_shards).select("qid", F.col("list_id").alias("visit")).join(asked, "qid")
    else:
        visits = asked.join(F.broadcast(shards))
    if want.name == "combined":
        source = index.nodes.select("shard", "id", "labels") if base is None else index.nodes.select("shard", "id").join(base.drop("vec"), "id")
        passing = source.join(small(asked.select("qid", "qlabels")), want.column(F.col("labels"), F.col("qlabels")))
        allowed = passing.groupBy("qid", F.col("shard").alias("visit")).agg(F.collect_list("id").alias("allowed"))  # at most a shard's rows
        visits = visits.join(allowed, ["qid", "visit"], "left").withColumn("allowed", F.coalesce("allowed", F.array().cast("array<bigint>")))
    else:
        visits = visits.withColumn("allowed", F.lit(None).cast("array<bigint>"))
    method, params, name = index.method, index.params, want.name

    def kernel(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        return _search(method, params, name, k, settings, left, right)

    lanes = lanes or lanes_for(queries.count(), index.shards, queries.sparkSession.sparkContext.defaultParallelism)
    copies = index.nodes.withColumn("lane", F.explode(F.sequence(F.lit(0), F.lit(lanes - 1))))
    dealt = visits.withColumn("lane", F.pmod(F.xxhash64("qid"), F.lit(lanes)).cast("int"))
    return copies.groupBy("shard", "lane").cogroup(dealt.groupBy("visit", "lane")).applyInPandas(kernel, FOUND)


def search(index: GraphIndex, queries: DataFrame, of: str | Constraint, k: int, base: DataFrame | None = None, **settings) -> DataFrame:
    """qid, rank, id, dist. `breadth` bounds the beam per shard (all of the shard without it)."""
    found = raw_search(index, queries, of, k, base, **settings).where("id is not null")
    return rerank(found, index.nodes.select("id", "vec"), queries, k)


def costs(found: DataFrame) -> DataFrame:
    """One row per query of the counters of a raw_search over all shards."""
    each = found.groupBy("qid", "shard").agg(*(F.first(c).alias(c) for c in ("dist_comps", "hops", "label_checks", "rounds")))  # equal in a query's rows of a shard
    return each.groupBy("qid").agg(*(F.sum(c).alias(c) for c in ("dist_comps", "hops", "label_checks")), F.max("rounds").alias("rounds"))


def edges(index: GraphIndex) -> DataFrame:
    """level, src, dst of every edge."""
    flat = index.nodes.select("id", F.posexplode("nbrs").alias("level", "to"))
    return flat.select("level", F.col("id").alias("src"), F.explode("to").alias("dst"))


def _reached(links: DataFrame, starts: DataFrame, max_hops: int) -> DataFrame:
    """id of the nodes within max_hops of starts along links (src, dst)."""
    frontier, seen = starts.distinct(), None
    for hop in range(max_hops + 1):
        frontier = written(frontier, "frontier")
        seen = frontier if seen is None else written(seen.unionByName(frontier), "reached")
        if hop == max_hops or not frontier.limit(1).count():
            break
        frontier = frontier.join(links, F.col("id") == F.col("src")).select(F.col("dst").alias("id")).distinct().join(seen, "id", "left_anti")
    return seen


def relational_beam(index: GraphIndex, queries: DataFrame, k: int, breadth: int, max_hops: int = 64) -> DataFrame:
    """The same walk as joins: all queries advance together, one hop per round. A reference, not the fast path.
    A beam as wide as the base drops nothing, so that all queries walk over the same nodes: the hops join nodes then, not pairs, and what they reach is scored in blocks."""
    from ..functions.distance import l2sq
    from pyspark.sql import Window

    links = written(edges(index).where("level = 0").select("src", "dst"), "links")
    vectors = index.nodes.select("id", "vec")
    starts = index.nodes.groupBy("shard").agg(F.min(F.struct((-F.col("level")).alias("l"), "id"))["id"].alias("id"))
    if breadth >= index.nodes.count():
        return block_search(index.nodes.join(_reached(links, starts.select("id"), max_hops), "id", "left_semi"), queries, "nofilter", k)
    asked = queries.select("qid", "qvec")
    best = asked.join(F.broadcast(starts.select("id"))).join(vectors, "id").select("qid", "id", l2sq(F.col("vec"), F.col("qvec")).alias("dist"), F.lit(False).alias("open_done"))
    seen = written(best, "beam")
    rank = Window.partitionBy("qid").orderBy("dist", "id")
    for _ in range(max_hops):
        top = seen.withColumn("r", F.row_number().over(rank))
        frontier = top.where((F.col("r") <= breadth) & ~F.col("open_done")).select("qid", "id")
        new = frontier.join(links, frontier.id == links.src).select("qid", F.col("dst").alias("id")).distinct().join(seen.select("qid", "id"), ["qid", "id"], "left_anti")
        scored = new.join(vectors, "id").join(small(asked), "qid").select("qid", "id", l2sq(F.col("vec"), F.col("qvec")).alias("dist"), F.lit(False).alias("open_done"))
        after = top.select("qid", "id", "dist", (F.col("open_done") | (F.col("r") <= breadth)).alias("open_done")).unionByName(scored)
        more = written(after, "beam")
        grown = more.where("not open_done").limit(1).count()
        seen = more
        if not grown:
            break
    return seen.withColumn("rank", F.row_number().over(rank)).where(F.col("rank") <= k).select("qid", "rank", "id", "dist")
