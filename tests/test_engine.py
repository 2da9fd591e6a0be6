"""Golden examples, invariants and plans of the filtered vector search engine."""

import itertools
import tracemalloc
from collections import Counter

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from vexil.functions import extensions
from vexil.functions.distance import fused, hamming, l2sq, register_sql
from vexil.functions.predicates import All, Any_, Containment, Equality, Not, Overlap, assert_fixed_length
from vexil.operators import bitmaps, exact, graph, ivf, kernels, quantize, two_level, walks
from vexil.plans import advisor, metrics, tune, workloads
from vexil.plans.planner import FilteredSearch, union_of_runs
from vexil.sources import carriers
from vexil.sources.store import IndexStore
from vexil.streaming import updates

GOLDEN = [(1, [4.0, 0.0], [1, 2, 3]), (2, [0.0, 5.0], [1, 2, 4]), (3, [2.0, 0.0], [1, 2]), (4, [3.0, 3.0], [3]), (5, [1.0, 0.0], [1]), (6, [0.0, 3.0], [2]), (7, [0.0, 6.0], [1, 2])]
BASE = "id bigint, vec array<double>, labels array<int>"
ASK = "qid bigint, qvec array<double>, qlabels array<int>"


@pytest.fixture(scope="module")
def golden(spark):
    return spark.createDataFrame(GOLDEN, BASE), spark.createDataFrame([(0, [0.0, 0.0], [1, 2])], ASK)


@pytest.fixture(scope="module")
def zipf(spark, sf):
    return carriers.dataset(spark, sf, "emb_zipf", 1)


def ids(found):
    return [r.id for r in found.orderBy("qid", "rank").collect()]


def rows(found):
    return sorted((r.qid, r.rank, r.id) for r in found.collect())


def test_golden_scenarios(golden):
    base, queries = golden
    want = {"nofilter": 5, "containment": 3, "equality": 3, "overlap": 5}
    passing = {"containment": {1, 2, 3, 7}, "equality": {3, 7}, "overlap": {1, 2, 3, 5, 6, 7}, "nofilter": set(range(1, 8))}
    for scenario, nearest in want.items():
        assert ids(exact.search(base, queries, scenario, 1, "column")) == [nearest]
        assert {r.id for r in exact.candidates(base, queries, scenario, "column").collect()} == passing[scenario]
        assert metrics.selectivity(base, queries, scenario).first().passing == len(passing[scenario])


def test_golden_bitmaps(golden):
    base, queries = golden
    numbered = bitmaps.with_ordinals(base)
    assert [r.ord for r in numbered.orderBy("id").collect()] == list(range(7))
    maps = bitmaps.build_label_bitmaps(numbered)

    def bits(found):
        byte = found.select(F.hex(F.substr("bm", F.lit(1), F.lit(1))).alias("b")).first().b
        return "".join(str(int(byte, 16) >> i & 1) for i in range(7))

    assert bits(maps.where("label = 1")) == "1110101" and bits(maps.where("label = 2")) == "1110011"
    assert bits(bitmaps.bitmap_all(maps, queries)) == "1110001" and bits(bitmaps.bitmap_any(maps, queries)) == "1110111"
    assert bits(bitmaps.bitmap_not(bitmaps.bitmap_any(maps, queries), queries, bitmaps.universe(numbered))) == "0001000"
    assert bitmaps.cardinality(bitmaps.bitmap_equal(maps, queries, numbered)).first().n == 2


def test_ordinals_are_dense_over_ranges(spark):
    numbered = bitmaps.with_ordinals(spark.range(0, 30000, 7).repartition(5), ranges=16)
    got = [r.ord for r in numbered.orderBy("id").collect()]
    assert got == list(range(len(got)))


def test_empty_label_sets(spark, golden):
    base, _ = golden
    base = base.unionByName(spark.createDataFrame([(8, [9.0, 9.0], [])], BASE))
    asked = spark.createDataFrame([(0, [0.0, 0.0], [])], ASK)
    for scenario, n in (("containment", 8), ("overlap", 0), ("equality", 1)):
        for route in ("column", "bitmap", "posting" if scenario != "equality" else "group"):
            assert exact.candidates(base, asked, scenario, route).count() == n
        index = graph.fit(base, "lattice", shards=1)
        assert graph.search(index, asked, scenario, 10).count() == n
    dirty = spark.createDataFrame([([3, None, 1, 3],), (None,)], "l array<int>").select(carriers.normalize_labels(F.col("l")).alias("l"))
    assert sorted(r.l for r in dirty.collect()) == [[], [1, 3]]


def test_lattice_golden():
    g = [frozenset(x) for x in ([1], [2], [1, 2], [1, 2, 3])]
    assert set(kernels.lattice_edges(g)) == {(g[0], g[2]), (g[1], g[2]), (g[2], g[3])}


def test_two_hops_find_what_one_misses():
    x = np.array([[0.0], [1.0], [2.0], [50.0]])
    s = kernels.Shard(np.arange(4), x, [(1,), (2,), (1,), (1,)], np.zeros(4, int), [[np.array([1])], [np.array([0, 2])], [np.array([1])], [np.array([2])]])
    allow = s.allow("containment", (1,))
    one = kernels.beam(x, np.array([2.0]), [0], 4, lambda i: s.at(i)[allow[s.at(i)]], kernels.Cost(), allow)
    two = kernels.search_twohop(s, np.array([2.0]), allow, 1, 1, kernels.Cost())
    assert [i for _, i in one] == [0] and two[0][1] == 2


def test_expansion_doubles(spark):
    base = spark.createDataFrame([(i, [float(i)], [1] if i == 24 else [2]) for i in range(60)], BASE)
    asked = spark.createDataFrame([(0, [0.0], [1])], ASK)
    assert workloads.exact_rounds(base, asked, "containment", 1, 10).first().rounds == 3


def test_exact_routes_agree(zipf):
    for scenario, routes in (("containment", ("column", "posting", "bitmap", "block")), ("overlap", ("column", "posting", "bitmap", "block")), ("equality", ("column", "group", "bitmap", "block"))):
        first, *others = [rows(exact.search(zipf.base, zipf.queries, scenario, 5, r)) for r in routes]
        assert first and all(o == first for o in others)


def test_selectivity_order(zipf):
    share = {s: {r.qid: r.passing for r in metrics.selectivity(zipf.base, zipf.queries, s).collect()} for s in ("containment", "overlap", "equality")}
    assert all(share["equality"][q] <= share["containment"][q] <= share["overlap"][q] for q in share["overlap"])


@pytest.mark.parametrize("kind", quantize.KINDS)
def test_quantizers(zipf, kind):
    index = quantize.fit(zipf.base, kind, bits=4)
    truth = exact.search(zipf.base, zipf.queries, "containment", 5)
    assert rows(quantize.search(index, zipf.queries, "containment", 5, 10_000)) == rows(truth)
    assert metrics.recall(quantize.search(index, zipf.queries, "containment", 5, 40), truth, 5) > 0.75
    assert 0 < quantize.reconstruction_error(zipf.base, index.codec) < 1
    assert quantize.search(index, zipf.queries, "containment", 5, reranked=False).count() > 0


def test_order_profiles_are_written_in_slices_by_hash_aggregation(spark, sf, monkeypatch):
    # one shuffle of all orders, and a set in each aggregation buffer (which spills after 128 orders), took more disk than the budget
    d, plain, parts = carriers.dataset(spark, sf, "basket_type", None), carriers.written_in_slices, []
    assert "ObjectHashAggregate" not in d.base._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(carriers, "SLICE_ORDERS", 500)
    monkeypatch.setattr(carriers, "written_in_slices", lambda df, tag, key, slices: parts.append(slices) or plain(df, tag, key, slices))
    kept = carriers.derived(spark, sf, "basket_type", d)
    assert parts == [min(carriers.MOST_SLICES, -(-carriers.read(spark, sf, "orders").count() // 500))] and parts[0] > 1
    want = {r.id: (r.vec, r.labels) for r in d.base.collect()}
    got = kept.base.collect()
    assert len(got) == len(want) and {r.id: (r.vec, r.labels) for r in got} == want


def test_ivf_rounds_keep_k_rows_a_query_and_task(zipf, monkeypatch):
    # all lists and a pool as wide as the base: no round may write its pairs
    kept, plain = [], ivf.written

    def seen(df, tag):
        out = plain(df, tag)
        if tag == "round":
            kept.append((out.count(), df.rdd.getNumPartitions()))
        return out

    index = ivf.fit(zipf.base, n_lists=4)
    monkeypatch.setattr(ivf, "written", seen)
    for of in ("overlap", "containment"):
        found = ivf.search(index, zipf.queries, of, 2, probes=4, pool=1 << 20)
        assert rows(found) == rows(exact.search(zipf.base, zipf.queries, of, 2))
    assert len(kept) == 2
    assert all(n <= 2 * parts * zipf.queries.count() for n, parts in kept)
    # a query visits its own lists only, and combined predicates still go by joins
    near = ivf.route(zipf.queries, index.centroids, 1).select("qid", "list_id")
    own = index.lists.join(near, "list_id").select("qid", "id")
    one = ivf.search(index, zipf.queries, "nofilter", 2, probes=1, most=1, pool=1 << 20)
    assert not one.join(own, ["qid", "id"], "left_anti").count()
    mixed = All((Containment(), Not(Overlap())))
    assert rows(ivf.search(index, zipf.queries, mixed, 2, probes=4)) == []


def test_ivf_widens_and_nests(zipf):
    index = ivf.fit(zipf.base, n_lists=8)
    truth = exact.search(zipf.base, zipf.queries, "overlap", 5)
    recalls = [metrics.recall(ivf.search(index, zipf.queries, "overlap", 5, probes=p, most=p, pool=10_000), truth, 5) for p in (1, 4, 8)]
    assert recalls == sorted(recalls) and recalls[-1] == 1.0
    assert rows(ivf.search(index, zipf.queries, "containment", 1, probes=1)) != []


@pytest.mark.parametrize("method", ["dense", "twohop", "postfilter", "shared", "stitched", "lattice"])
def test_graphs_find_and_obey(zipf, method):
    index = graph.fit(zipf.base, method, shards=2)
    for scenario in ("containment", "overlap", "equality"):
        truth = exact.search(zipf.base, zipf.queries, scenario, 5)
        whole = graph.search(index, zipf.queries, scenario, 5)
        assert rows(whole) == rows(truth)
        small = graph.search(index, zipf.queries, scenario, 5, breadth=40, l0=40)
        assert metrics.recall(small, truth, 5) > 0.6
        assert metrics.invalid_rows(small, zipf.base, zipf.queries, scenario).count() == 0
        assert small.groupBy("qid", "id").count().where("count > 1").count() == 0
    costs = graph.costs(graph.raw_search(index, zipf.queries, "containment", 5, breadth=20, l0=20)).collect()
    assert all(r.dist_comps > 0 for r in costs)


def test_fused_and_two_level(spark, sf):
    d = carriers.dataset(spark, sf, "doc_fixed4", 4)
    assert assert_fixed_length(d.base) == 4
    truth = rows(exact.search(d.base, d.queries, "fixed", 3))
    for options in ({}, {"additive": True}, {"start": "waves"}):
        index = graph.fit(d.base, "fused", shards=2, options=options)
        assert rows(graph.search(index, d.queries, "fixed", 3, additive=options.get("additive", False))) == truth
    parts = two_level.fit(d.base, 4, 3)
    assert rows(two_level.search(parts, d.queries, 3, probes=4)) == truth
    some = two_level.search(parts, d.queries, 3, probes=1)
    assert metrics.invalid_rows(some, d.base, d.queries, "fixed").count() == 0


def test_lattice_edges_imply_inclusion(zipf):
    index = graph.fit(zipf.base, "lattice", shards=1)
    labels = {r.id: set(r.labels) for r in index.nodes.collect()}
    for r in graph.edges(index).collect():
        assert labels[r.src] < labels[r.dst] if r.level == 1 else labels[r.src] == labels[r.dst]


def test_stitched_bridges_share_labels(zipf):
    index = graph.fit(zipf.base, "stitched", shards=1)
    labels = {r.id: set(r.labels) for r in index.nodes.collect()}
    assert all(labels[r.src] & labels[r.dst] for r in graph.edges(index).collect())


def test_relational_beam_equals_the_kernel(zipf):
    index, asked = graph.fit(zipf.base, "postfilter", shards=1), zipf.queries.limit(4)
    want = rows(exact.search(zipf.base, asked, "nofilter", 5, "block"))
    assert rows(graph.relational_beam(index, asked, 5, 10_000)) == want
    assert metrics.recall(graph.relational_beam(index, asked, 5, 40), exact.search(zipf.base, asked, "nofilter", 5, "block"), 5) > 0.7


def test_combined_predicates(zipf):
    mixed = All((Overlap(), Not(Equality())))
    truth = rows(exact.search(zipf.base, zipf.queries, mixed, 5))
    for method in ("dense", "twohop", "postfilter"):
        assert rows(FilteredSearch(zipf.base, method, shards=2).search(zipf.queries, mixed, 5, breadth=10_000, l0=10_000)) == truth
    assert (Overlap() & Containment()).name == "combined" and isinstance(Overlap() | Containment(), Any_)
    with pytest.raises(ValueError):
        FilteredSearch(zipf.base, "lattice").search(zipf.queries, mixed)
    lattice = FilteredSearch(zipf.base, "lattice")
    either = Any_((Equality(), Overlap()))
    assert rows(union_of_runs(lattice, zipf.queries, ["equality", "overlap"], 5, breadth=10_000)) == rows(exact.search(zipf.base, zipf.queries, either, 5))


def test_planner_checks(spark, zipf):
    with pytest.raises(ValueError):
        FilteredSearch(zipf.base, "fused")
    with pytest.raises(ValueError):
        FilteredSearch(zipf.base).search(spark.createDataFrame([(0, [1.0], [1])], ASK), "overlap")
    assert FilteredSearch(zipf.base).resolve("equality", 10).route == "group"
    assert rows(FilteredSearch(zipf.base, "ivfpq", n_lists=4).search(zipf.queries, "overlap", 3, probes=4, pool=10_000)) == rows(exact.search(zipf.base, zipf.queries, "overlap", 3))


def test_plans(zipf):
    def plan(df):
        return df._jdf.queryExecution().executedPlan().toString()

    for scenario in ("containment", "overlap", "equality"):
        # prepared side by side: rarest labels and size checks run before this plan
        found = plan(exact.candidates(zipf.base, zipf.queries.where("size(qlabels) > 0"), scenario).where("qid is not null").select("qid", "id"))
        assert scenario == "containment" or "NestedLoop" not in found
    assert plan(exact.search(zipf.base, zipf.queries, "overlap", 5)).count("WindowGroupLimit") == 2


def test_interpolation_rank_front(spark):
    runs = tune.fixture(spark)
    at = {(r.config_id, r.target): r.qps for r in tune.qps_at(runs, [0.7, 0.8, 0.95, 0.6]).collect()}
    assert at[("a", 0.8)] == pytest.approx(750) and at[("a", 0.95)] is None and at[("a", 0.7)] == 1000 and at[("a", 0.6)] == 1000
    picks = tune.pick_representatives(tune.rank_configs(tune.qps_at(runs, [0.8, 0.9, 0.95])))
    assert picks.count() == 2
    pts = spark.createDataFrame([(0.8, 900.0), (0.85, 700.0), (0.84, 600.0), (0.95, 100.0)], "recall double, qps double")
    assert {r.recall for r in metrics.pareto(pts, []).collect()} == {0.8, 0.85, 0.95}
    boxes = tune.split_space("postfilter", workloads.GRIDS["postfilter"])
    assert len(boxes) == 4 and {c.subspace for c in boxes} == {0, 1, 2, 3}
    assert len(tune.tune_none("fused").params) == 9
    counts = {m: len(p) for m, p in graph.DEFAULTS.items()}
    assert counts == {"dense": 3, "twohop": 2, "lattice": 4, "postfilter": 2, "shared": 3, "stitched": 4, "fused": 9}


def test_tuning_flow(zipf):
    values = {"degree": [4, 12], "breadth": [16]}
    runs, picks = tune.tune("postfilter", zipf.base, zipf.queries.limit(5), values, ["overlap"], 5, [5, 20], share=0.6)
    assert runs.count() == 4 and picks.count() == 2
    assert set(tune.build_full("postfilter", picks, values, zipf.base)) == {r.config_id for r in picks.collect()}


def test_samples_nest(zipf):
    sets = [{r.id for r in workloads.nested_sample(zipf.base, p).collect()} for p in (10, 25, 50, 100)]
    assert all(a <= b for a, b in itertools.pairwise(sets)) and sets[-1] == {r.id for r in zipf.base.collect()}
    assert {r.id for r in tune.sample_base(zipf.base, 0.2).collect()} <= {r.id for r in tune.sample_base(zipf.base, 0.5).collect()}


def test_advice():
    assert not advisor.supports("lattice", "combined") and not advisor.supports("fused", "overlap")
    for _, profile, want in advisor.ADVICE:
        got = advisor.recommend(profile)
        assert ",".join(got) == want and all(advisor.supports(m, profile.constraint) for m in got)


def test_sql_functions(spark):
    register_sql(spark)
    r = spark.sql("select l2sq(array(1D, 2D), array(3D, 5D)) d, labels_contain(array(1, 2), array(2)) c, hamming_distance(array(1, 2), array(1, 3)) h, cosine_distance(array(1D, 0D), array(0D, 1D)) o").first()
    assert (r.d, r.c, r.h, r.o) == (13.0, True, 1, 1.0)
    one = spark.createDataFrame([([1.0, 2.0], [0.0, 0.0], [1, 2], [1, 3])], "a array<double>, b array<double>, f array<int>, g array<int>")
    r = one.select(l2sq(F.col("a"), F.col("b")).alias("d"), hamming(F.col("f"), F.col("g")).alias("h"), fused(F.lit(2.0), F.lit(1), 2, 1.0).alias("w"), fused(F.lit(2.0), F.lit(1), 2, 1.0, True).alias("v")).first()
    assert (r.d, r.h, r.w, r.v) == (5.0, 1, 3.0, 3.0)


def test_index_store(spark, zipf, tmp_path):
    store = IndexStore(spark, str(tmp_path))
    index = graph.fit(zipf.base, "postfilter", shards=2)
    assert store.save("layers", {"nodes": index.nodes}, index.params, {"nodes": ["shard"]}) == 1
    assert store.save("layers", {"nodes": index.nodes}, index.params) == 2
    tables, settings = store.load("layers")
    assert tables["nodes"].count() == index.nodes.count() and settings == index.params
    assert store.bytes("layers", 1) > 0 and store.versions("none") == []


def test_updates(spark, zipf):
    delta = spark.createDataFrame([(1, [0.0] * 64, [9]), (9000, [1.0] * 64, [9])], BASE)
    after = updates.apply_delta(zipf.base, delta, spark.createDataFrame([(2,), (9000,)], "id bigint"))
    got = {r.id: list(r.labels) for r in after.where("id in (1, 2, 9000)").collect()}
    assert got == {1: [9]}
    index = graph.fit(zipf.base, "twohop", shards=2)
    relabelled = updates.relabel(index.nodes, zipf.base.select("id", F.array(F.lit(77)).alias("labels")).where("id < 50"))
    index.nodes = relabelled
    asked = zipf.queries.withColumn("qlabels", F.array(F.lit(77)))
    fresh = zipf.base.withColumn("labels", F.when(F.col("id") < 50, F.array(F.lit(77))).otherwise(F.col("labels")))
    assert rows(graph.search(index, asked, "containment", 5)) == rows(exact.search(fresh, asked, "containment", 5))


def test_streams(spark, sf, tmp_path):
    events = updates.events(spark, sf).orderBy("ts")
    n, day = events.count(), F.unix_timestamp(F.col("ts").cast("timestamp"))
    cuts = [0, *(int(x) for x in events.select(day.cast("double").alias("t")).approxQuantile("t", [0.33, 0.66], 0.01)), 1 << 40]
    for low, high in itertools.pairwise(cuts):  # files in the order of time
        events.where((day >= low) & (day < high)).coalesce(1).write.mode("append").parquet(f"{tmp_path}/events")
    stream = updates.change_stream(spark, f"{tmp_path}/events", events.schema, "1000 days")
    folded = updates.stateful_labels(stream).writeStream.outputMode("update").format("memory").queryName("label_state").option("checkpointLocation", f"{tmp_path}/c1").trigger(availableNow=True).start()
    folded.awaitTermination(180)
    seen = {}
    for r in spark.table("label_state").collect():
        seen.setdefault(r.id, []).append(list(r.labels))
    want = {r.id: list(r.labels) for r in updates.current_labels(updates.changes(events)).collect()}
    assert set(seen) == set(want) and all(want[i] in seen[i] for i in want)
    counted = updates.label_frequency_stream(updates.change_stream(spark, f"{tmp_path}/events", events.schema)).writeStream.outputMode("complete").format("memory").queryName("label_counts").option("checkpointLocation", f"{tmp_path}/c2").trigger(availableNow=True).start()
    counted.awaitTermination(180)
    assert 0 < spark.table("label_counts").agg(F.sum("count")).first()[0] <= n


def test_query_stream(spark, zipf, tmp_path):
    zipf.queries.write.parquet(f"{tmp_path}/q")
    asked = spark.readStream.schema(zipf.queries.schema).parquet(f"{tmp_path}/q")
    updates.query_stream(asked, lambda batch: exact.search(zipf.base, batch, "overlap", 3), f"{tmp_path}/out", f"{tmp_path}/c").awaitTermination(120)
    assert rows(spark.read.parquet(f"{tmp_path}/out")) == rows(exact.search(zipf.base, zipf.queries, "overlap", 3))


def test_registered_queries_import():
    import __spark_entry__ as entry

    names = entry.queries()
    assert {"truth_containment", "lattice_edges", "support_matrix"} <= set(names) and set(entry.oracle_sql()) <= set(names)


def test_dense_lists_recover_what_they_prune():
    """Each pruned neighbour stands in a list that the walk expands."""
    x = np.random.default_rng(4).normal(size=(300, 8))
    degree, gamma, keep = 8, 3, 6
    full = kernels.knn(x, degree * gamma)
    _, lists = kernels.dense(x, np.arange(300), degree, gamma, keep, degree * gamma)
    pruned = 0
    for own, (kept,) in zip(full, lists):
        seen = set(kept.tolist()).union(*(lists[j][0].tolist() for j in kept[keep:].tolist()))
        pruned += len(set(own[: degree * gamma].tolist()) - set(kept.tolist()))
        assert set(own[: degree * gamma].tolist()) <= seen
    assert pruned > 0


def test_asked_labels_follow_label_frequency(spark, sf):
    """A label is asked for about as often as rows hold it."""
    d = carriers.dataset(spark, sf.replace("sf0.001", "sf0.1"), "emb_zipf", 1)
    held, asked = (Counter(x for r in rows for x in r[0]) for rows in (d.rows.select("labels").collect(), d.queries.select("qlabels").collect()))
    for label in (1, 2, 3, 5):
        assert abs(asked[label] / asked.total() - held[label] / held.total()) < 0.06


def test_costs_add_up_over_shards_with_equal_counters(spark):
    found = spark.createDataFrame([(1, 0, 5, 0.1, 7, 2, 3, 1), (1, 0, 6, 0.2, 7, 2, 3, 1), (1, 1, 8, 0.3, 7, 2, 3, 1), (2, 1, None, None, 4, 1, 0, 2)], graph.FOUND)
    assert {tuple(r) for r in graph.costs(found).collect()} == {(1, 14, 4, 6, 1), (2, 4, 1, 0, 2)}


def test_walks_without_restarts_stay_in_reach():
    chain = [[np.array([i + 1] if i + 1 < 4 else [], int)] for i in range(8)]  # nodes 4 to 7 can't be reached from node 0
    shard = kernels.Shard(np.arange(8), np.arange(8.0)[:, None], [(1,)] * 8, np.zeros(8, int), chain)
    q, allow = np.array([0.0]), shard.allow("overlap", (1,))
    for restart, want in ((False, 4), (True, 6)):
        found = kernels.search_twohop(shard, q, allow, 6, 6, kernels.Cost(), restart=restart)
        assert len(found) >= want and (restart or {i for _, i in found} <= set(range(4)))
    assert shard.centre(1) == shard.centre() and shard.minimal(frozenset([1])) == [0] and shard.codes(1).tolist() == [[1]] * 8


def test_dictionary_over_ranges(spark):
    rows = spark.createDataFrame([(v, None if i % 3 else "x") for i, v in enumerate(["b", "a", None, "c", "a"])], "host string, kind string")
    found = carriers.label_dictionary(rows, ["kind", "host"], ranges=3).orderBy("label").collect()
    assert [tuple(r) for r in found] == [("host", "a", 1), ("host", "b", 2), ("host", "c", 3), ("kind", "x", 4)]
    assert carriers.label_dictionary(rows.limit(0), ["host"]).count() == 0


def test_faults_of_vectors(spark):
    rows = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [1.0]), (4, [float("nan"), 0.0]), (5, [None, 0.0]), (6, [float("inf"), 0.0])], "id bigint, vec array<double>")
    found = {r.id: r.fault for r in rows.select("id", carriers.vector_fault(F.col("vec"), 2).alias("fault")).collect()}
    assert found == {1: "none", 2: "null", 3: "length", 4: "not finite", 5: "not finite", 6: "not finite"}
    assert carriers.assert_vectors(rows.where("id = 1")) == 2 and carriers.assert_vectors(rows.limit(0)) is None
    for bad in (2, 3, 4, 5, 6):
        with pytest.raises(ValueError):
            carriers.assert_vectors(rows.where(F.col("id").isin(1, bad)))


def test_lanes_answer_alike(spark, zipf):
    index = graph.fit(zipf.base, "twohop")
    one, several = (rows(graph.search(index, zipf.queries, "overlap", 10, breadth=40, lanes=n)) for n in (1, 3))
    assert one == several and one


def test_medoids_and_table_function(spark):
    points = [(1, 0, [0.0, 0.0]), (2, 0, [2.0, 0.0]), (3, 0, [1.0, 0.5]), (4, 1, [5.0, 5.0]), (5, 2, [1.0, 1.0]), (6, 2, [1.0, 1.0]), (7, 3, None)]
    base = spark.createDataFrame(points, "id bigint, label int, vec array<double>")
    assert {tuple(r) for r in extensions.medoids(base, "label").collect()} == {(0, 3), (1, 4), (2, 5)}
    extensions.register_extensions(spark)
    by_sql = spark.sql("select label, medoid(id, vec) as medoid from {base} where vec is not null group by label", base=base)
    assert {tuple(r) for r in by_sql.collect()} == {(0, 3), (1, 4), (2, 5)}
    table = base.select("id", "vec", F.array("label").alias("labels"), (F.col("id") % 2).alias("shard"))
    near = spark.sql("select * from knn_candidates(table(select * from {t}) partition by (shard), array(0D, 0D), array(0), 1)", t=table)
    assert {tuple(r) for r in near.collect()} == {(1, 0.0), (2, 4.0)}


def test_reports_and_counters(spark, sf, zipf):
    back = workloads.reports(spark, sf)
    runs = tune.event_runs(spark, sf)
    assert back.count() == 2 * runs.count() > 0 and back.drop("form").exceptAll(runs.unionByName(runs)).count() == 0
    got, truth = workloads.search_counters(zipf, "containment", 10).first(), exact.search(zipf.base, zipf.queries, "containment", 10)
    assert got.found == truth.count() and got.deepest == 10


def test_block_keeps_the_smallest_of_many_copies(spark):
    copies = spark.createDataFrame([(i, [1.0, 2.0], [1]) for i in range(60, 0, -1)] + [(99, [1.0, 2.5], [1]), (100, [1.0, 2.0], [2])], BASE).coalesce(1)
    asked = spark.createDataFrame([(0, [1.0, 2.0], [1]), (1, [0.0, 0.0], [])], ASK)
    for metric in ("l2", "ip", "cosine"):
        assert rows(exact.search(copies, asked.where("qid = 0"), "containment", 5, "block", metric)) == rows(exact.search(copies, asked.where("qid = 0"), "containment", 5, "column", metric))
    assert [r.id for r in exact.search(copies, asked, "containment", 5, "block").where("qid = 1").orderBy("rank").collect()] == [1, 2, 3, 4, 5]


def test_block_matrices_are_bounded(spark):
    """6,000 queries with one set of labels and 8,000 rows: whole matrices of these took 384 MB each."""
    rng = np.random.default_rng(5)
    asked = spark.createDataFrame([(i, v, [1]) for i, v in enumerate(rng.normal(size=(6_000, 4)).tolist())], ASK)
    batch = pa.RecordBatch.from_arrays([pa.array(np.arange(8_000)), pa.array(rng.normal(size=(8_000, 4)).tolist()), pa.array([[1]] * 8_000, pa.list_(pa.int32()))], ["id", "vec", "labels"])
    block = exact.QueryBlock(asked)
    tracemalloc.start()
    found = sum(b.num_rows for b in exact.nearest(block, iter([batch]), "overlap", 10))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert found == 60_000 and peak < 150e6


def test_assignment_to_equal_centroids(spark):
    base = spark.createDataFrame([(i, [0.3, 0.1], [1]) for i in range(40)] + [(50, [0.3, 0.2], [1])], BASE).coalesce(1)
    centres = spark.createDataFrame([(i, [0.3, 0.1]) for i in range(30, 5, -1)], "list_id bigint, cvec array<double>")
    assert {r.list_id for r in ivf.assign(base, centres).collect()} == {6}


@pytest.mark.parametrize("kind", quantize.KINDS)
def test_codes_rerank_where_rows_lie(spark, zipf, kind):
    """No pairs of a query and all passing rows leave a task: the plan has no join, and each task at most k rows a query."""
    index = quantize.fit(zipf.base, kind)
    found = quantize.search(index, zipf.queries, "overlap", 5, 1 << 20)
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    part = quantize.scan_exact(index.codes.coalesce(1), index.codec, zipf.queries, "overlap", 5, 1 << 20)
    assert part.groupBy("qid").count().agg(F.max("count")).first()[0] <= 5


def test_selectivity_meets_sets_not_rows(spark, zipf, monkeypatch):
    many = zipf.base.withColumn("id", F.explode(F.array(F.col("id"), F.col("id") + 1_000_000, F.col("id") + 2_000_000)))
    sets, seen, real = zipf.base.select("labels").distinct().count(), [], exact.candidates
    for name in ("containment", "overlap", "equality", "nofilter"):
        want = {r.qid: r.n for r in exact.candidates(many, zipf.queries, name, "column").groupBy("qid").agg(F.count("*").alias("n")).collect()}
        monkeypatch.setattr(exact, "candidates", lambda b, *a, **k: (seen.append(b.count()), real(b, *a, **k))[1])
        assert {r.qid: r.passing for r in metrics.selectivity(many, zipf.queries, name).where("passing > 0").collect()} == want
        monkeypatch.undo()
    assert max(seen) == sets


def test_reach_widens_until_enough_is_found(spark, zipf):
    def cut(asked, width):  # a search that sees the first rows only
        return exact.search(zipf.base.where(F.col("id") < width), asked, "overlap", 5, "column")

    assert tune.reach(cut, zipf.base, zipf.queries, "overlap", 5, 10) > 100
    assert tune.reach(lambda asked, width: exact.search(zipf.base, asked, "overlap", 5), zipf.base, zipf.queries, "overlap", 5, 10) == 10


def test_runs_and_requests_come_from_events(spark, sf):
    found = __spark_entry__.queries()
    for name in ("config_pick", "config_rank", "cube_method_scenario", "method_advice", "minmax_scatter", "pareto_front", "qps_interpolated", "report_export", "rollup_scenario_k", "scenario_average", "support_matrix"):
        if name != "report_export":  # which reads its own files
            assert any("events.parquet" in f for f in found[name](spark, sf).inputFiles()), name
    n = carriers.read(spark, sf, "events").count()
    assert found["method_advice"](spark, sf).agg(F.sum("requests")).first()[0] == n
    assert found["support_matrix"](spark, sf).where("method = 'prefilter'").agg(F.sum("requests")).first()[0] == n


def test_exact_rounds_count_positions(spark):
    base = spark.createDataFrame([(i, [float(i // 3)], [1] if i % 7 == 0 else [2]) for i in range(200)], BASE)
    asked = spark.createDataFrame([(0, [0.0], [1]), (1, [40.0], [1]), (2, [0.0], [3])], ASK)
    last = exact.search(base, asked, "containment", 5).where("rank = 5")
    assert {r.qid: r.pos for r in exact.positions(base, asked, last).collect()} == {0: 29, 1: sum((abs(i // 3 - 40.0), i) <= max(sorted((abs(j // 3 - 40.0), j) for j in range(0, 200, 7))[:5]) for i in range(200))}
    assert {r.qid: r.rounds for r in workloads.exact_rounds(base, asked, "containment", 5, 16).collect()}[2] == 5  # 16 to 256 rows


def test_exhaustive_fused_walk_visits_once(monkeypatch):
    rng = np.random.default_rng(3)
    x, labels = rng.normal(size=(80, 5)), [tuple(int(v) + 3 * i for i, v in enumerate(own)) for own in rng.integers(0, 3, (80, 2))]
    x[40:] = x[:40]
    s = kernels.Shard(np.arange(80), x, labels, np.zeros(80, int), kernels.fused(x, labels, 6, 10, 2, 5, 5, 6, 10, 40.0, 2.0))
    q, asked, codes = rng.normal(size=5), labels[7], s.codes(2)
    walked = kernels.beam(s.x, q, [s.centre()], 80, s.at, kernels.Cost(), None, lambda c: kernels.fuse(kernels.sq(x[c], q), kernels.label_gap(codes[c], np.array(asked)), 2, 2.0, False))
    monkeypatch.setattr(kernels, "beam", None)  # a walk that cuts nothing needs no heap
    cost = kernels.Cost()
    assert [i for _, i in kernels.search_fused(s, q, asked, 80, 2.0, cost, strict=False)] == [i for _, i in walked] and cost.hops == len(walked)
    own = kernels.search_fused(s, q, asked, 80, 2.0, kernels.Cost())
    assert [i for _, i in own] == [i for _, i in sorted((float(kernels.sq(x[i : i + 1], q)[0]), i) for _, i in walked if labels[i] == asked)]


def test_waves_meet_in_bounded_matrices(monkeypatch):
    rng = np.random.default_rng(4)
    x, labels = rng.normal(size=(200, 5)), [tuple(int(v) + 3 * i for i, v in enumerate(own)) for own in rng.integers(0, 3, (200, 2))]
    x[100:] = x[:100]
    whole = kernels.fused(x, labels, 6, 10, 2, 5, 5, 6, 10, 40.0, 2.0, start="waves")
    seen, usual = [], np.partition
    monkeypatch.setattr(kernels.np, "partition", lambda a, *more, **named: seen.append(a.size) or usual(a, *more, **named))
    monkeypatch.setattr(kernels, "MATRIX", 500)
    cut = kernels.fused(x, labels, 6, 10, 2, 5, 5, 6, 10, 40.0, 2.0, start="waves")
    assert all(np.array_equal(a[0], b[0]) for a, b in zip(whole, cut)) and seen and max(seen) <= 500


def test_relational_beam_as_wide_as_the_base_hops_over_nodes(zipf, monkeypatch):
    index, queries = graph.fit(zipf.base, "postfilter", shards=2), zipf.queries.limit(12)
    made, usual = [], graph.written
    monkeypatch.setattr(graph, "written", lambda df, tag: made.append(df.columns) or usual(df, tag))
    wide = graph.relational_beam(index, queries, 5, 1 << 20)
    assert sorted(map(tuple, wide.collect())) == sorted(map(tuple, exact.search(zipf.base, queries, "nofilter", 5).collect()))
    assert not any("qid" in columns for columns in made)
    # few hops reach few nodes, as in the kernel's own walk
    links = graph.edges(index).where("level = 0").select("src", "dst")
    near = graph._reached(links, index.nodes.orderBy("id").limit(1).select("id"), 1)
    start = index.nodes.orderBy("id").first()
    assert {r.id for r in near.collect()} == {start.id, *start.nbrs[0]}


def test_sweeps_fit_a_shared_base_once(spark, zipf, monkeypatch):
    made, usual = [], workloads.searcher
    monkeypatch.setattr(workloads, "searcher", lambda base, m: made.append(m) or usual(base, m))
    other = carriers.Dataset(zipf.base.where("id % 2 = 0"), zipf.queries, zipf.rows)
    found = workloads.sweep(spark, [("a", zipf), ("b", carriers.Dataset(zipf.base, zipf.queries.where("qid % 4 = 1"), zipf.rows)), ("c", other)], "overlap", ("prefilter",))
    assert {(r.setting, r.recall) for r in found.collect()} == {("a", 1.0), ("b", 1.0), ("c", 1.0)} and made == ["prefilter"] * 2


def _scalar(method, s, p, of, q, asked, k, breadth, restart):
    cost, allow = kernels.Cost(), s.allow(of, asked)
    if method == "postfilter":
        found = kernels.search_postfilter(s, q, allow, k, breadth, 2, len(s.ids), cost)
    elif method == "twohop":
        found = kernels.search_twohop(s, q, allow, k, breadth, cost, 2, restart)
    elif method == "dense":
        found = kernels.search_dense(s, q, allow, k, breadth, int(p["keep"]), int(p["degree"] * p["gamma"]), cost, 0, restart)
    elif method == "lattice":
        found = kernels.search_lattice(s, q, of, asked, k, breadth, cost)
    elif method == "fused":
        found = kernels.search_fused(s, q, asked, breadth, p["label_weight"], cost)
    else:
        found = kernels.search_labelled(s, q, allow, asked, k, breadth, cost)
    return found, cost


@pytest.mark.parametrize("method", list(graph.DEFAULTS))
def test_walks_together_are_the_walks_one_by_one(method):
    rng, p, n = np.random.default_rng(3), graph.DEFAULTS[method], 260
    x = rng.normal(size=(n, 6))
    x[40:60] = x[:20]  # equal distances
    for fixed in (False, True):
        if method == "fused" and not fixed:
            continue
        labels = [tuple(int(rng.integers(3)) + 3 * j for j in range(3)) if fixed else tuple(sorted(rng.choice(8, rng.integers(4), replace=False).tolist())) for _ in range(n)]
        nodes = graph._build(method, p, {}, pd.DataFrame({"shard": 0, "id": 3 * np.arange(n), "vec": list(x), "labels": [list(a) for a in labels]}))
        shard, q = graph._shard(nodes), rng.normal(size=(12, 6))
        asked = [labels[rng.integers(n)][: 3 if fixed else 2] for _ in q]
        for of in ("fixed",) if fixed else ("containment", "overlap", "equality"):
            for breadth, restart in ((4, False), (4, True), (30, False), (n, True)):
                got, costs = walks.search(method, p, shard, of, q, asked, None, 3, breadth, {"restart": restart, "l0": breadth})
                assert list(zip(got, costs)) == [_scalar(method, shard, p, of, *one, 3, breadth, restart) for one in zip(q, asked)]


@pytest.mark.parametrize("shared", [False, True])
def test_candidates_pruned_together_are_those_pruned_one_by_one(shared, monkeypatch):
    monkeypatch.setattr(kernels, "MATRIX", 2_000)  # several rounds
    rng = np.random.default_rng(4)
    x, labels = rng.normal(size=(90, 5)), [tuple(rng.choice(70, 3, replace=False).tolist()) for _ in range(90)]
    lists = [rng.choice(90, rng.integers(0, 20), replace=False) for _ in range(90)]
    lists = [c[np.argsort(kernels.sq(x[c], x[i]))] for i, c in enumerate(lists)]
    sets = [frozenset(a) for a in labels]
    covers = (lambda i, r, c: sets[i] & sets[c] <= sets[r]) if shared else None
    got = kernels.diverse_lists(lists, x, 6, 1.2, kernels.label_bits(labels) if shared else None)
    assert [c.tolist() for c in got] == [kernels.diverse(i, c, x, 6, 1.2, covers).tolist() for i, c in enumerate(lists)]


def test_repair_attaches_many_parts_without_a_pass_for_each(monkeypatch):
    x = np.repeat(np.random.default_rng(5).normal(size=(60, 4)), 3, axis=0)  # copies that know only one another
    lists, measured, usual = [np.setdiff1d(np.arange(i - i % 3, i - i % 3 + 3), [i]) for i in range(180)], [], kernels.sq
    monkeypatch.setattr(kernels, "sq", lambda a, b: measured.append(len(a)) or usual(a, b))
    kernels.repair(lists, x, 0)
    assert kernels.reach(lists, 0).all() and sum(measured) < 60 * 10


def test_lanes_keep_cores_busy_without_many_copies():
    assert graph.lanes_for(5_128, 4, 6) == 5 and graph.lanes_for(100, 4, 6) == 1 and graph.lanes_for(100_000, 50, 6) == 10
