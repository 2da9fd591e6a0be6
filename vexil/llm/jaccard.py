"""Operator 10: exact n-gram Jaccard self-join by universe partition and pigeonhole.

Sets are distinct word shingles. For sizes within a band, two sets with similarity of at least
`percent` % differ in at most H shingles. The shingle universe is cut into units by hash, so many that a
set fills H + 8 of them; then any such pair agrees on eight filled units at least. Each filled unit of a
set is indexed under its content (one signature). Where a band's units collide too often, by a cost estimate
from a bounded sample of sets, neighbouring units are merged into one that is indexed with its
one-deletion neighbourhood: it may differ in one shingle and so stands for the two units. The
allocation changes cost only, never the outcome.

1. Equal sets become one node (partial aggregation), so copies never meet in a bucket.
2. Signatures of a single node are dropped by aggregating least and greatest node; so are nodes with fewer
   shared keys than any linked pair has.
3. Each bucket names its most popular node (most meetings over all its keys): the centre of a group of near copies.
   Each node is verified against the one centre that it shares most keys with; that finds nearly all links,
   and its centre, linked or not, gives each node a family.
4. Exactness: buckets whose nodes are all joined by now are closed. What is still open is compared within families,
   then, for nodes that still meet other families, within families made of these meetings alone, and at last within buckets, where a
   node leaves out its most frequent keys. All are cut into windows of set sizes and blocks of bounded size; two blocks meet in one task, where an incidence product
   gives all intersections and only links that join components leave. Blocks of one component don't meet.

Outcome: each document with its component; links between different texts are never missed, and
all pairs of a group are never made.

Cases: null or wordless text is an empty set and its own component; with fewer words than `k`
the whole sequence is the one shingle; rows with a null doc_id are their own components (null);
rows that share a doc_id share a component only if their texts are linked.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache, partial

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import as_bytes, free_names, grams, hash_words, made, materialise, mix, release, release_since, signed, slices

BAND = 1.5
SLICES = 4  # parts of the key space, dealt out one after the other: the disk of one part
BLOCK_NODES, BLOCK_BYTES = 2_048, 8_000_000
ROUND_ITEMS = 16_000_000  # shingles that a round of block pairs may send, however few all sets have
SPARE = 8  # filled units on which any linked pair agrees
WIDE = 2  # size classes by which the windows of a large group move on
KIN = 3  # shared keys that make a node one of its centre's family (families move cost only)


def shingle_sets(texts: list[bytes], k: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    words, offsets = hash_words([t.lower() for t in texts])
    whole = grams(words, k)
    out = []
    for lo, hi in zip(offsets[:-1], offsets[1:]):
        if hi - lo >= k:
            out.append(np.unique(whole[lo : hi - k + 1]))
        else:
            out.append(grams(words[lo:hi], int(hi - lo), 100) if hi > lo else np.zeros(0, np.uint64))
    return out


class Bands:
    """Size bands and the units of each: band b holds sizes in [edge(b), edge(b + 1))."""

    def __init__(self, percent: int):
        if not 70 <= percent <= 100:
            raise ValueError("percent must lie in 70..100: a partner could else lie two bands up")
        self.percent = percent
        self.edges = [1]
        self.counts: dict[int, int] = {}

    def edge(self, b: int) -> int:
        while len(self.edges) <= b:
            self.edges.append(max(self.edges[-1] + 1, int(self.edges[-1] * BAND)))
        return self.edges[b]

    def of(self, n: int) -> list[int]:
        """The own band, and the next one if a partner may lie there."""
        b = 0
        while self.edge(b + 1) <= n:
            b += 1
        return [b, b + 1] if n * 100 >= self.percent * self.edge(b + 1) else [b]

    def differ(self, b: int) -> int:
        """Most shingles in which linked sets of band b differ: sizes add up to s, s * (1 - t) / (1 + t)."""
        return (2 * (self.edge(b + 1) - 1) * (100 - self.percent)) // (100 + self.percent)

    def units(self, b: int) -> int:
        """Units of band b, so many that a set of its least size likely fills differ + SPARE of them;
        0 where linked sets must be equal: those are one node already."""
        if b not in self.counts:
            h, low = self.differ(b), self.edge(b)
            m = h + SPARE if h else 0
            while h and m < 4 * (h + SPARE):
                empty = m * math.exp(-low / m)
                if m - empty - 2 * math.sqrt(empty) >= h + SPARE:
                    break
                m += 1
            self.counts[b] = m
        return self.counts[b]


@lru_cache(4_096)
def _cuts(m: int) -> np.ndarray:
    return (np.arange(1, m, dtype=np.float64) * (2.0**64 / m)).astype(np.uint64)


def unit_ranges(s: np.ndarray, m: int) -> np.ndarray:
    """Borders in the sorted set s of m equal ranges of the hashed universe."""
    return np.concatenate([[0], np.searchsorted(s, _cuts(m)), [len(s)]])


def signatures(s: np.ndarray, bands: Bands, merged: dict[int, frozenset[int]]) -> tuple[np.ndarray, int]:
    """Index keys of one set, and how many keys any linked set has in common with it.

    merged: for a band, the pairs (j, j+1) of units, by even j, that are merged. Nothing is promised with
    merged units or too few filled; of two bands the smaller promise counts.
    """
    n, needs = len(s), []
    weight = mix(s, 21)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(weight)])
    out = [np.zeros(0, np.uint64)]
    for b in bands.of(len(s)) if len(s) else []:
        if not (m := bands.units(b)):
            continue
        at = unit_ranges(s, m)
        sums = total[at[1:]] - total[at[:-1]]
        pairs = sorted(j for j in merged.get(b, ()) if j + 1 < m)
        alone = np.setdiff1d(np.arange(m), [i for j in pairs for i in (j, j + 1)]) if pairs else np.arange(m)
        filled = alone[at[alone + 1] > at[alone]]
        # Linked sets differ in H units at most. If either fills H + SPARE units, they agree on SPARE filled ones,
        # so empty units need no key; sets that fill fewer keep them, for partners that do so too.
        enough = len(filled) + 2 * len(pairs) >= bands.differ(b) + SPARE
        used = filled if enough else alone
        largest = min(bands.edge(b + 1) - 1, n * 100 // bands.percent)
        needs.append((len(filled) if enough and not pairs else 0) - (n + largest) * (100 - bands.percent) // (100 + bands.percent))
        out.append(mix(sums[used] + mix(used.astype(np.uint64), 1000 + b), 22))
        for j in pairs:
            whole, base = sums[j : j + 2].sum(dtype=np.uint64), mix(np.array([j], np.uint64), 5000 + b)
            near = np.concatenate([np.array([whole]), whole - weight[at[j] : at[j + 2]]])
            out.append(np.unique(mix(near + base, 23)))
    return np.concatenate(out), max(0, min(needs, default=0))


def _set_table(docs: DataFrame, k: int, percent: int, merged: dict[int, frozenset[int]]) -> DataFrame:
    """doc_id, n_shingles, node (hash of the set) and the set's keys, in a column for each slice of the key space."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bands = Bands(percent)
        for batch in batches:
            texts = as_bytes(batch.column(1))
            for lo, hi in slices(texts):
                sets = shingle_sets(texts[lo:hi], k)
                signed_up = [signatures(s, bands, merged) for s in sets]
                keys = [x[0] for x in signed_up]
                node = [node_hash(s) for s in sets]
                parts, flat = [], np.concatenate(keys)
                whose, part = np.repeat(np.arange(len(keys)), [len(x) for x in keys]), flat % np.uint64(SLICES)
                for i in range(SLICES):
                    own = part == i
                    at = np.concatenate([[0], np.cumsum(np.bincount(whose[own], minlength=len(keys)))]).astype(np.int32)
                    parts.append(pa.ListArray.from_arrays(pa.array(at), pa.array(signed(flat[own]))))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(lo, hi - lo).cast(pa.int64()), batch.column(2).slice(lo, hi - lo), pa.array([len(s) for s in sets], pa.int64()), pa.array(node, pa.int64()), pa.array([x[1] for x in signed_up], pa.int32()), *parts],
                    ["doc_id", "text_hash", "n_shingles", "node", "need", *(f"keys{i}" for i in range(SLICES))],
                )

    return docs.select("doc_id", "text", F.xxhash64("text").alias("h")).mapInArrow(run, "doc_id bigint, text_hash bigint, n_shingles bigint, node bigint, need int, " + ", ".join(f"keys{i} array<bigint>" for i in range(SLICES)))


def allocate(docs: DataFrame, k: int, percent: int, sample: int = 4_000, weight: float = 0.05) -> dict[int, frozenset[int]]:
    """Pairs of units to merge, per band. Cost of a unit: its signatures plus weight (what a comparison within a block costs next to a signature
    that is dealt out) times the sets that a set is expected to meet there; estimated from about `sample` documents, picked by hash."""
    size = max(1, docs.count())
    picked = docs.where(F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(1 << 30)) < int(min(1.0, sample / size) * (1 << 30))).select("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bands = Bands(percent)
        for batch in batches:
            texts, rows = as_bytes(batch.column(0)), []
            for lo, hi in slices(texts):
                for s in shingle_sets(texts[lo:hi], k):
                    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(s, 21))])
                    for b in bands.of(len(s)) if len(s) else []:
                        if (m := bands.units(b)) > 1:
                            at = unit_ranges(s, m)
                            node = int(signed(total[-1:])[0])
                            rows += [(b, j - j % 2, False, x, node, len(s)) for j, x in enumerate(signed(total[at[1:]] - total[at[:-1]]).tolist()) if x]
                            rows += [(b, j, True, x, node, len(s)) for j, x in zip(range(0, m - 1, 2), signed(total[at[2::2]] - total[at[:-2:2]]).tolist())]
            kinds = (pa.int32(), pa.int32(), pa.bool_(), pa.int64(), pa.int64(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], ["band", "even", "joint", "sig", "node", "n"])

    seen = picked.mapInArrow(run, "band int, even int, joint boolean, sig bigint, node bigint, n int").dropDuplicates(["band", "even", "joint", "sig", "node"])
    c = seen.groupBy("band", "even", "joint", "sig").agg(F.count("*").alias("c"), F.sum("n").alias("n"))
    # a row for each pair of units of each band in the sample: as many as the longest text needs, not the corpus
    per = c.groupBy("band", "even").agg(
        *(F.sum(F.when(F.col("joint") == j, F.col("c") * (F.col("c") - 1)).otherwise(0)).alias(f"pairs{int(j)}") for j in (False, True)), F.sum(F.when(F.col("joint"), F.col("c")).otherwise(0)).alias("sets"), F.sum(F.when(F.col("joint"), F.col("n")).otherwise(0)).alias("n")
    )
    grown, bands = max(1.0, size / sample), Bands(percent)
    out: dict[int, set[int]] = {}
    for r in per.where("sets > 50").collect():
        alone = 2 + weight * grown * r.pairs0 / r.sets
        joint = 1 + 2 * r.n / r.sets / bands.units(r.band) + weight * grown * r.pairs1 / r.sets
        if joint < alone:
            out.setdefault(r.band, set()).add(r.even)
    return {b: frozenset(x) for b, x in out.items()}


def components(links: DataFrame) -> DataFrame:
    """node, comp (smallest node reachable) for all nodes of links (a, b).

    Rounds of contraction: each node hooks to its least neighbour, chains are shortened by pointer jumps, and the
    links between what remains apart are carried on; they shrink to nothing within a few rounds.
    """
    left = materialise(links.selectExpr("least(a, b) as a", "greatest(a, b) as b").where("a != b").distinct(), "links")
    label = materialise(links.selectExpr("a as node").unionByName(links.selectExpr("b as node")).distinct().withColumn("comp", F.col("node")), "label")
    while left.limit(1).count():
        parent = materialise(left.groupBy(F.col("b").alias("x")).agg(F.min("a").alias("p")), "parent")
        while True:
            one, two = parent.selectExpr("x as p", "p as q"), parent.selectExpr("x as q", "p as r")
            jumped = parent.join(one, "p", "left").join(two, "q", "left").select("x", F.coalesce("r", "q", "p").alias("p"), F.col("r").isNotNull().alias("moved"))
            jumped = materialise(jumped, "parent")
            moved = jumped.where("moved").limit(1).count()
            parent = jumped.select("x", "p")
            if not moved:
                break
        label = materialise(label.join(parent, F.col("comp") == F.col("x"), "left").select("node", F.coalesce("p", "comp").alias("comp")), "label")
        first = left.join(parent, F.col("a") == F.col("x"), "left").select(F.coalesce("p", "a").alias("a"), "b")
        both = first.join(parent, F.col("b") == F.col("x")).select("a", F.col("p").alias("b"))  # b always has a parent
        left = materialise(both.selectExpr("least(a, b) as a", "greatest(a, b) as b").where("a != b").distinct(), "links")
    return label


def node_hash(s: np.ndarray) -> int | None:
    """The node of a set; an empty set has none."""
    return int(mix(np.array([mix(s, 31).sum(dtype=np.uint64) + np.uint64(len(s))], np.uint64), 32).view(np.int64)[0]) if len(s) else None


def _node_sets(docs: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """node, n, items (sorted 64-bit hashes) for the nodes of wanted (doc_id, node); of the texts of an id, only those with the node's own set."""
    known = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").join(wanted, "doc_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, nodes = as_bytes(batch.column(0)), batch.column(1).to_pylist()
            for lo, hi in slices(texts):
                own = [(node, s) for node, s in zip(nodes[lo:hi], shingle_sets(texts[lo:hi], k)) if node == node_hash(s)]
                yield pa.RecordBatch.from_arrays([pa.array([node for node, _ in own], pa.int64()), pa.array([len(s) for _, s in own], pa.int64()), pa.array([s.tobytes() for _, s in own], pa.binary())], ["node", "n", "items"])

    return known.select("text", "node").mapInArrow(run, "node bigint, n bigint, items binary").dropDuplicates(["node"])


def _compare_blocks(frame: pd.DataFrame, percent: int) -> pd.DataFrame:
    """Links that join components, between sides 0 and 1 of a block pair (or within side 0), from one incidence product."""
    frame = frame.sort_values(["side", "node"])
    sets = [np.frombuffer(x, np.uint64) for x in frame["items"]]
    node, comp, side = frame["node"].to_numpy(), frame["comp"].to_numpy(), frame["side"].to_numpy()
    size = np.array([len(x) for x in sets])
    row = np.repeat(np.arange(len(sets)), size)
    _, code, seen = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = seen[code] > 1  # a shingle of one set adds to no intersection
    row, code = row[shared], code[shared]
    _, code = np.unique(code, return_inverse=True)
    left, right = np.flatnonzero(side == 0), np.flatnonzero(side == (1 if side.any() else 0))
    common = np.zeros((len(left), len(right)), np.float32)
    order = np.argsort(code, kind="stable")
    row, code = row[order], code[order]
    last = int(code[-1]) + 1 if len(code) else 0
    for lo in range(0, last, 2_048):
        a, b = np.searchsorted(code, [lo, lo + 2_048])
        part = np.zeros((len(sets), min(2_048, last - lo)), np.float32)
        part[row[a:b], code[a:b] - lo] = 1
        common += part[left] @ part[right].T
    linked = 100 * common >= percent * (size[left][:, None] + size[right][None, :] - common)
    root = {c: c for c in comp.tolist()}

    def find(c: int) -> int:
        while root[c] != c:
            root[c] = root[root[c]]
            c = root[c]
        return c

    out = []
    for i, j in zip(*np.nonzero(linked & (comp[left][:, None] != comp[right][None, :]))):
        x, y = find(int(comp[left[i]])), find(int(comp[right[j]]))
        if x != y:
            root[max(x, y)] = min(x, y)
            out.append((int(node[left[i]]), int(node[right[j]])))
    return pd.DataFrame(out, columns=["a", "b"], dtype=np.int64)


def _windows(groups: DataFrame, percent: int) -> DataFrame:
    """groups (family, node, comp, n), where a family too large for one block falls into windows of set sizes, such that any two sizes that
    allow a link have a window in common. A node stands in one window, or in two that overlap."""
    sums = materialise(groups.groupBy("family").agg(F.count("*").alias("c"), F.sum("n").alias("total")).where((F.col("c") > BLOCK_NODES) | (F.col("total") * 8 > BLOCK_BYTES)).select(F.col("family").alias("_large")), "large")
    # sizes that allow a link lie less than a class's width apart, so in one class or in two neighbouring ones
    width = max(math.log(100 / percent), 0.01) * 1.000001
    at = F.floor(F.log(F.greatest("n", F.lit(1)).cast("double")) / width)
    own = F.floor(at / WIDE)
    places = F.when((at % WIDE == 0) & (own > 0), F.array(own - 1, own)).otherwise(F.array(own))
    cut = groups.join(sums, F.col("family") == F.col("_large"), "left").withColumn("w", F.explode(F.when(F.col("_large").isNull(), F.array(F.lit(-1).cast("bigint"))).otherwise(places)))
    return materialise(cut.select(F.when(F.col("_large").isNull(), F.col("family")).otherwise(F.xxhash64("family", "w")).alias("family"), "node", "comp", "n"), "windows")


def _block_links(groups: DataFrame, sets: DataFrame, percent: int) -> DataFrame | None:
    """Links within groups (family, node, comp, n) between nodes of different components.

    A group larger than a block falls into windows of sizes. What is still larger is cut into blocks of bounded size, those of its largest
    component apart, which needn't meet one another; any other two blocks meet in one task. A node's set is sent once for each block it
    meets. Rounds of at most the volume of all sets keep the disk in bounds: their number follows how often sets are sent, not the input.
    Sets are joined with what they meet once, whatever the rounds.
    """
    groups = _windows(groups, percent)
    comps = materialise(groups.groupBy("family", "comp").agg(F.count("*").alias("c"), F.sum("n").alias("total")), "comps")
    size = comps.groupBy("family").agg(F.max(F.struct("c", "total", "comp")).alias("m"), F.sum("c").alias("c"), F.sum("total").alias("total")).where("c > m.c")
    cut = lambda c, total: F.ceil(F.greatest(c / BLOCK_NODES, total * 8 / BLOCK_BYTES)).cast("int")
    size = size.withColumn("whole", cut(F.col("c"), F.col("total")) == 1)
    size = materialise(size.select("family", F.col("m.comp").alias("main"), F.when(F.col("whole"), 0).otherwise(cut(F.col("m.c"), F.col("m.total"))).alias("mains"), F.when(F.col("whole"), 1).otherwise(cut(F.col("c") - F.col("m.c"), F.col("total") - F.col("m.total"))).alias("others")), "blocks")
    if not size.limit(1).count():
        release(groups, comps, size)
        return None
    in_main = (F.col("comp") == F.col("main")) & (F.col("mains") > 0)
    place = F.xxhash64("node", F.lit(3))
    placed = groups.join(size, "family").withColumn("own", F.when(in_main, F.pmod(place, F.greatest("mains", F.lit(1)))).otherwise(F.col("mains") + F.pmod(place, "others")).cast("int"))
    met = F.sequence(F.when(in_main, F.col("mains")).otherwise(0), F.col("mains") + F.col("others") - 1)
    met = F.transform(met, lambda o: F.struct(F.least("own", o).alias("i"), F.greatest("own", o).alias("j"), (F.col("own") > o).cast("int").alias("side")))
    visits = placed.select("node", F.col("n").cast("bigint").alias("n"), F.transform(met, lambda v: F.struct(F.col("family").alias("family"), v["i"].alias("i"), v["j"].alias("j"), v["side"].alias("side"), F.col("comp").alias("comp"))).alias("met"))
    visits = materialise(visits.groupBy("node").agg(F.first("n").alias("n"), F.flatten(F.collect_list("met")).alias("met")), "visits")
    bound = max(ROUND_ITEMS, sets.agg(F.sum("n")).first()[0])
    rounds = max(1, -(-visits.agg(F.sum(F.col("n") * F.size("met"))).first()[0] // bound))
    held, out = visits.select("node", "met").join(sets.select("node", "items"), "node"), None
    if rounds > 1:
        held = materialise(held, "held", 1_000)
    for r in range(rounds):
        own = F.filter("met", lambda v: F.pmod(F.xxhash64(v["family"], v["i"], v["j"]), F.lit(rounds)) == r)  # noqa: B023
        part = held.select("node", "items", F.explode(own).alias("v")).select("node", "items", "v.*")
        found = materialise(part.groupBy("family", "i", "j").applyInPandas(partial(_compare_blocks, percent=percent), "a bigint, b bigint"), "links", 512)
        out = found if out is None else out.unionByName(found)
    release(groups, comps, size, visits, *([held] if rounds > 1 else []))
    return out


def _members(table: DataFrame, common: int, passes: int = 2) -> DataFrame:
    """key, node, n, need, pop of the buckets with two nodes or more, for nodes that have as many such keys as they need.
    pop: rows (copies too) that a node meets, over all its keys."""
    parts = []
    for i in range(SLICES):
        rows = table.where("node is not null").select("node", F.col("n_shingles").cast("int").alias("n"), F.greatest("need", F.lit(common)).alias("need"), F.explode(f"keys{i}").alias("key"))
        keys = materialise(rows.groupBy("key").agg(F.min("node").alias("lo"), F.max("node").alias("hi"), F.count("*").alias("c")).where("lo != hi").select("key", "c"), "keys")
        parts.append(materialise(rows.join(keys, "key").groupBy("key", "node").agg(F.first("n").alias("n"), F.first("need").alias("need"), F.first("c").alias("c")), "members"))
        release(keys)
    members = parts[0]
    for p in parts[1:]:
        members = members.unionByName(p)
    for turn in range(passes):
        enough = members.groupBy("node", "need").agg(F.count("*").alias("keys"), F.sum("c").alias("pop")).where("keys >= need").select("node", "pop")
        kept = members.join(enough, "node")
        shared = kept.groupBy("key").count().where("count > 1").select("key")
        kept = kept.join(shared, "key", "left_semi")
        members = materialise(kept.select("key", "node", "n", "need", "c", *(["pop"] if turn == passes - 1 else [])), "members")
    release(*parts)
    return members.drop("c")


def _open(rows: DataFrame, label: str, passes: int = 2) -> DataFrame:
    """Rows (key, node, n, need, comp, family) of the keys that several labels have, for nodes with as many such keys as they need."""
    for _ in range(passes):
        span = rows.groupBy("key").agg(F.min(label).alias("lo"), F.max(label).alias("hi")).where("lo != hi").select("key")
        live = rows.join(span, "key", "left_semi")
        enough = live.groupBy("node", "need").count().where("count >= need").select("node")
        rows = materialise(live.join(enough, "node", "left_semi"), "live")
    return rows


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets are linked."""
    both = pairs.select("a", "b").join(sets.selectExpr("node as a", "items as x"), "a").join(sets.selectExpr("node as b", "items as y"), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3)):
                x, y = (np.frombuffer(z.as_buffer(), np.uint64) for z in (x, y))
                common = len(x) + len(y) - len(np.unique(np.concatenate([x, y])))
                keep.append(100 * common >= percent * (len(x) + len(y) - common))
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    return both.select("a", "b", "x", "y").mapInArrow(run, "a bigint, b bigint")


def _roots(parents: DataFrame) -> DataFrame:
    """node, root from a forest (node, parent), by pointer jumps."""
    while True:
        up = parents.select(F.col("node").alias("parent"), F.col("parent").alias("up"))
        jumped = materialise(parents.join(up, "parent", "left").select("node", F.coalesce("up", "parent").alias("parent"), F.col("up").isNotNull().alias("moved")), "roots")
        parents = jumped.select("node", "parent")
        if not jumped.where("moved").limit(1).count():
            return parents.withColumnRenamed("parent", "root")


def _families(rows: DataFrame) -> DataFrame:
    """node, root: what the rows (key, node) have in common once more, each node with the centre that it shares most keys with."""
    counts = rows.groupBy("key").agg(F.count("*").alias("c"))
    popular = materialise(rows.select("key", "node").join(counts, "key").groupBy("node").agg(F.sum("c").alias("pop")), "popular")
    centres = rows.select("key", "node").join(popular, "node").groupBy("key").agg(F.max(F.struct("pop", "node"))["node"].alias("centre"))
    met = rows.select("key", "node").join(centres, "key").where("node != centre").groupBy("node", "centre").count().where(f"count >= {KIN}")
    return _roots(materialise(met.groupBy("node").agg(F.max(F.struct("count", "centre"))["centre"].alias("parent")), "best"))


def link_nodes(members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """node, comp from bucket members (key, node, n, need, pop), for the nodes that links join."""
    # the centre of a bucket is its greatest by (pop, node): an order of all nodes, so that centres form a forest
    centres = materialise(members.groupBy("key").agg(F.max(F.struct("pop", "node", "n")).alias("p")).select("key", F.col("p.node").alias("centre"), F.col("p.n").alias("m")), "centres")
    met = members.join(centres, "key").where(f"node != centre and 100 * least(n, m) >= {percent} * greatest(n, m)").groupBy("node", "centre").count()
    best = materialise(met.groupBy("node").agg(F.max(F.struct("count", "centre")).alias("p")).select(F.col("node").alias("a"), F.col("p.centre").alias("b"), F.col("p.count").alias("shared")), "best")
    links = materialise(_verified(best, sets, percent), "links", 256)
    linked = best.join(links, ["a", "b"], "left_semi").select("a", "b")
    kin = best.where(f"shared >= {KIN}").select("a", "b").unionByName(linked).distinct()
    comps, families = (_roots(x.selectExpr("a as node", "b as parent")) for x in (links, kin))
    rows = members.select("key", "node", "n", "need").join(comps.withColumnRenamed("root", "comp"), "node", "left").join(families.withColumnRenamed("root", "family"), "node", "left")
    live = _open(materialise(rows.withColumns({x: F.coalesce(x, "node") for x in ("comp", "family")}), "rows"), "comp")
    inner = _block_links(live.select("family", "node", "comp", "n").distinct(), sets, percent)
    if inner is not None:
        links = links.unionByName(inner)
    found = components(links)
    again = live.drop("comp").join(found, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    # pairs of one family are settled: what is left meets another family, and another component
    across = _open(_open(materialise(again, "rows"), "family"), "comp", 1)
    # those that meet other families in many keys at once get families anew, so that they meet there and not in each of these keys
    anew = across.drop("family").join(_families(across).withColumnRenamed("root", "family"), "node", "left").withColumn("family", F.coalesce("family", "node"))
    anew = materialise(anew, "rows")
    second = _block_links(anew.select("family", "node", "comp", "n").distinct(), sets, percent)
    if second is not None:
        found = components(found.selectExpr("comp as a", "node as b").unionByName(second))
    left = anew.drop("comp").join(found, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    across = _open(_open(materialise(left, "rows"), "family"), "comp", 1)
    sizes = materialise(across.groupBy("key").agg(F.count("*").alias("c")), "sizes")
    # a node shares `need` keys with any linked one, so they also share one if it leaves out its need - 1 most frequent
    # ones: the rarest of what two nodes share has at least need - 1 shared keys before it in either
    frequent = Window.partitionBy("node").orderBy(F.desc("c"), "key")
    rare = materialise(across.join(sizes, "key").withColumn("r", F.row_number().over(frequent)).where("r >= need").select(F.col("key").alias("family"), "node", "comp", "n"), "rare")
    outer = _block_links(rare, sets, percent)
    if outer is not None:
        found = components(found.selectExpr("comp as a", "node as b").unionByName(outer))
    release(centres, live, across, rare)
    return found


def join_components(docs: DataFrame, k: int = 3, percent: int = 90, merged: dict[int, frozenset[int]] | None = None) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest linked doc_id) of every document, and the row's text_hash and comp: rows
    with equal comp are linked (null without a set or id)."""
    if merged is None:
        merged = allocate(docs, k, percent)
    keyed = materialise(_set_table(docs, k, percent, merged), "keyed")
    table = materialise(keyed.select("doc_id", "text_hash", "n_shingles", "node"), "sets")
    common = SPARE if not any(merged.values()) else SPARE // 2  # a merged unit stands for two
    members = _members(keyed, common)
    release(keyed)
    own = table.where("node is not null and doc_id is not null").groupBy("node").agg(F.min("doc_id").alias("doc_id"))
    wanted = own.join(members.select("node").distinct(), "node", "left_semi")
    sets = materialise(_node_sets(docs, wanted, k), "nodes", 1_000)
    label = link_nodes(members, sets, percent)
    named = own.join(label, "node", "left").select("node", "doc_id", F.coalesce("comp", "node").alias("comp"))
    least = named.groupBy("comp").agg(F.min("doc_id").alias("component_id"))
    final = materialise(named.join(least, "comp").select(F.col("node").alias("_node"), "component_id", "comp"), "components")
    release(sets, members)
    # without a set, or without an id, a row is its own component
    shown = table.join(final, (F.col("node") == F.col("_node")) & F.col("doc_id").isNotNull(), "left")
    return shown.select("doc_id", "text_hash", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"), "comp")


def keep_one(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """The rows of docs without near copies: of each component one row stays, of the smallest doc_id and, if several texts have it, of the
    smallest text hash. Rows without a set or id stay."""
    before = made()
    found = materialise(join_components(docs, k, percent).where("comp is not null").select("doc_id", "text_hash", "component_id", "comp"), "found")
    first = found.where("doc_id = component_id").groupBy("comp").agg(F.min("text_hash").alias("first"))
    gone = found.join(first, "comp").where("doc_id != component_id or text_hash != first").select("doc_id", "text_hash").distinct()
    again = found.where("doc_id = component_id").groupBy("doc_id", "text_hash").count().where("count > 1").select("doc_id", "text_hash")
    marks = materialise(gone.withColumn("again", F.lit(False)).unionByName(again.join(gone, ["doc_id", "text_hash"], "left_anti").withColumn("again", F.lit(True))), "marks")
    release_since(before, marks)
    own, mark = free_names(["_doc", "_again"], docs.columns)
    named = marks.select(F.col("doc_id").alias(own), "text_hash", F.col("again").alias(mark))
    met = (F.col("doc_id") == F.col(own)) & (F.xxhash64("text") == F.col("text_hash"))
    left = docs.join(named.drop(mark), met, "left_anti")
    if not marks.where("again").limit(1).count():
        return left
    # equal rows under one id: one of them
    twice = docs.join(named.where(F.col(mark)).drop(mark), met, "left_semi")
    return left.unionByName(twice.dropDuplicates(["doc_id", "text"]))
