"""Graph construction and traversal on one shard, in NumPy. No Spark in here.

Nodes are row numbers of a shard. Every search returns candidates and cost counters:
distance computations, hops (expanded nodes), label checks and rounds.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np

Neighbours = Callable[[int], np.ndarray]
MATRIX = 1 << 20  # entries of one matrix


@dataclass
class Cost:
    dist_comps: int = 0
    hops: int = 0
    label_checks: int = 0
    rounds: int = 0


@dataclass
class Shard:
    ids: np.ndarray
    x: np.ndarray
    labels: list[tuple[int, ...]]
    level: np.ndarray
    nbrs: list[list[np.ndarray]]  # node -> level -> neighbours
    members: dict[int, np.ndarray] = field(default_factory=dict)  # label -> bitset over nodes
    size: np.ndarray | None = None
    starts: dict[object, object] = field(default_factory=dict)  # entries worked out once for all queries

    def __post_init__(self) -> None:
        n = len(self.ids)
        for i, own in enumerate(self.labels):
            for a in own:
                self.members.setdefault(a, np.zeros(n, bool))[i] = True
        self.size = np.array([len(a) for a in self.labels])

    def allow(self, scenario: str, asked: tuple[int, ...]) -> np.ndarray:
        """Filter map from the label bitsets: AND, OR, or AND and a check of equality."""
        n = len(self.ids)
        maps = [self.members.get(a, np.zeros(n, bool)) for a in asked]
        if scenario == "nofilter":
            return np.ones(n, bool)
        if scenario == "overlap":
            return np.logical_or.reduce(maps) if maps else np.zeros(n, bool)
        out = np.logical_and.reduce(maps) if maps else np.ones(n, bool)
        return out & (self.size == len(asked)) if scenario in ("equality", "fixed") else out

    @cached_property
    def groups(self) -> dict[frozenset[int], int]:
        """The first node of each label set."""
        out: dict[frozenset[int], int] = {}
        for i, own in enumerate(self.labels):
            out.setdefault(frozenset(own), i)
        return out

    def centre(self, label: int | None = None) -> int:
        """The medoid of a label's nodes, or of all."""
        if ("centre", label) not in self.starts:
            rows = np.arange(len(self.x)) if label is None else np.flatnonzero(self.members[label])
            self.starts["centre", label] = medoid(self.x, rows)
        return self.starts["centre", label]

    def minimal(self, want: frozenset[int]) -> list[int]:
        """Nodes of the label sets that hold the asked one and no smaller such set."""
        if want not in self.starts:
            kept: list[frozenset[int]] = []
            for g in sorted((g for g in self.groups if want <= g), key=len):
                if not any(m < g for m in kept):
                    kept.append(g)
            self.starts[want] = [self.groups[g] for g in kept]
        return self.starts[want]

    def reached(self, start: int) -> np.ndarray:
        """All nodes that a walk on level 0 from start can visit."""
        if ("reached", start) not in self.starts:
            self.starts["reached", start] = np.flatnonzero(reach([self.at(i) for i in range(len(self.x))], start))
        return self.starts["reached", start]

    def labelled(self, start: int, asked: tuple[int, ...]) -> np.ndarray:
        """The nodes reached from start that have just the asked labels."""
        if ("labelled", start) not in self.starts:
            own: dict[tuple[int, ...], list[int]] = {}
            for i in self.reached(start).tolist():
                own.setdefault(self.labels[i], []).append(i)
            self.starts["labelled", start] = {a: np.array(rows) for a, rows in own.items()}
        return self.starts["labelled", start].get(asked, np.zeros(0, int))

    def codes(self, width: int) -> np.ndarray:
        """Label sets of that many labels as a matrix; others are all -1."""
        if ("codes", width) not in self.starts:
            self.starts["codes", width] = np.array([list(a) if len(a) == width else [-1] * width for a in self.labels]).reshape(len(self.x), width)
        return self.starts["codes", width]

    def at(self, i: int, level: int = 0) -> np.ndarray:
        own = self.nbrs[i]
        return own[level] if level < len(own) else np.zeros(0, int)


def sq(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    diff = x - q
    return np.einsum("ij,ij->i", diff, diff)


# ------------------------------------------------------------------ building


def knn(x: np.ndarray, k: int, block: int = 1_024) -> list[np.ndarray]:
    """The k nearest other rows of each row, nearest first (ties by row)."""
    n = len(x)
    k = min(k, n - 1)
    if k <= 0:
        return [np.zeros(0, int)] * n
    norm, out = (x * x).sum(axis=1), []
    for lo in range(0, n, block):
        d = norm[None, :] - 2 * x[lo : lo + block] @ x.T
        d[np.arange(len(d)), np.arange(lo, lo + len(d))] = np.inf
        near = np.argpartition(d, k - 1, axis=1)[:, :k]
        value = np.take_along_axis(d, near, axis=1)
        order = np.lexsort((near, value), axis=1)
        out += list(np.take_along_axis(near, order, axis=1))
    return out


def diverse(i: int, cand: np.ndarray, x: np.ndarray, degree: int, alpha: float, covers: Callable[[int, int, int], bool] | None = None) -> np.ndarray:
    """Keep a candidate unless a kept one is closer to it by alpha (and covers what the two share)."""
    if len(cand) <= 1:
        return cand[:degree]
    pts = x[cand]
    own = sq(pts, x[i])
    norm = (pts * pts).sum(axis=1)
    between = norm[:, None] + norm[None, :] - 2 * pts @ pts.T
    kept: list[int] = []
    for j in range(len(cand)):
        if len(kept) >= degree:
            break
        if not any(alpha * between[r, j] < own[j] and (covers is None or covers(i, int(cand[r]), int(cand[j]))) for r in kept):
            kept.append(j)
    return cand[kept]


def label_bits(labels: list[tuple[int, ...]]) -> np.ndarray:
    """Label sets as lines of bits, 64 to a word."""
    at = {a: i for i, a in enumerate(sorted({a for own in labels for a in own}))}
    out = np.zeros((len(labels), max(1, -(-len(at) // 64))), np.uint64)
    for i, own in enumerate(labels):
        for a in own:
            out[i, at[a] // 64] |= np.uint64(1 << at[a] % 64)
    return out


def diverse_lists(lists: list[np.ndarray], x: np.ndarray, degree: int, alpha: float, bits: np.ndarray | None = None, over: int = 1) -> list[np.ndarray]:
    """`diverse` of each row's candidates, many rows at once; lists of `over` candidates at most stay. With bits, a kept candidate covers the labels that the row and the other share."""
    size = np.array([len(c) for c in lists], int)
    out = [c[:degree] if len(c) <= 1 else c for c in lists]
    order = np.argsort(size, kind="stable")
    order = order[size[order] > max(1, over)]
    lo = 0
    while lo < len(order):
        many, entries = len(order) - lo, lambda r: r * int(size[order[lo + r - 1]]) * max(int(size[order[lo + r - 1]]), x.shape[1])  # noqa: B023
        while many > 1 and entries(many) > MATRIX:
            many = -(-many // 2)
        own = order[lo : lo + many]
        lo += many
        m = int(size[own[-1]])
        there = np.arange(m) < size[own][:, None]
        c = np.zeros((many, m), int)
        c[there] = np.concatenate([lists[i] for i in own.tolist()])
        pts = x[c]
        gap = pts - x[own][:, None, :]
        dist, norm = np.einsum("rmd,rmd->rm", gap, gap), np.einsum("rmd,rmd->rm", pts, pts)
        between = alpha * (norm[:, :, None] + norm[:, None, :] - 2 * pts @ pts.transpose(0, 2, 1))
        common = None if bits is None else bits[own][:, None, :] & bits[c]
        kept, count = np.zeros((many, m), bool), np.zeros(many, int)
        for j in range(m):
            t = np.flatnonzero(there[:, j] & (count < degree))
            if len(t):
                kept[t, j] = True
                count[t] += 1
                behind = between[t, j] < dist[t]
                if common is not None:
                    behind &= ~(common[t] & ~bits[c[t, j]][:, None, :]).any(axis=2)
                there[t] &= ~behind
                there[t, j] = True
        for i, row, stays in zip(own.tolist(), c, kept):
            out[i] = row[stays]
    return out


def nearest_first(src: np.ndarray, dst: np.ndarray, x: np.ndarray) -> list[np.ndarray]:
    """The distinct other ends dst of each row, nearest first (ties by row)."""
    n = len(x)
    key = np.unique((src * n + dst)[src != dst])
    src, dst = key // n, key % n
    dist = np.zeros(len(key))
    for lo in range(0, len(key), MATRIX // 16):
        gap = x[dst[lo : lo + MATRIX // 16]] - x[src[lo : lo + MATRIX // 16]]
        dist[lo : lo + MATRIX // 16] = np.einsum("ij,ij->i", gap, gap)
    return np.split(dst[np.lexsort((dst, dist, src))], np.searchsorted(src, np.arange(1, n))) if n else []


def with_reverse(lists: list[np.ndarray], x: np.ndarray, cap: int, alpha: float | None, bits: np.ndarray | None = None) -> list[np.ndarray]:
    """Add the reverse of each edge; lists over cap are pruned (diverse, or nearest first without alpha)."""
    src = np.repeat(np.arange(len(lists)), [len(c) for c in lists])
    dst = np.concatenate([np.zeros(0, int), *lists]).astype(int)
    both = nearest_first(np.concatenate([src, dst]), np.concatenate([dst, src]), x)
    return diverse_lists(both, x, cap, alpha, bits, cap) if alpha else [c[:cap] for c in both]


def reach(lists: list[np.ndarray], start: int, inside: np.ndarray | None = None, seen: np.ndarray | None = None) -> np.ndarray:
    """Nodes reachable from start (over nodes inside only)."""
    seen = np.zeros(len(lists), bool) if seen is None else seen
    stack = [start]
    seen[start] = True
    while stack:
        for j in lists[stack.pop()].tolist():
            if not seen[j] and (inside is None or inside[j]):
                seen[j] = True
                stack.append(j)
    return seen


def repair(lists: list[np.ndarray], x: np.ndarray, start: int, inside: np.ndarray | None = None) -> None:
    """Attach what start can't reach to its nearest reached node, both ways."""
    want = np.ones(len(lists), bool) if inside is None else inside
    seen = reach(lists, start, inside)
    rest = np.flatnonzero(want & ~seen)
    norm = (x * x).sum(axis=1) if len(rest) else np.zeros(0)
    off = 4e-10 * norm.max(initial=0)  # more than the products can be off
    step = max(1, MATRIX // max(1, len(x)))
    while len(rest):  # the distances of some at a time; what is attached on the way drops out
        some = rest[:step]
        rough = norm[None, :] - 2 * x[some] @ x.T
        for i, d in zip(some.tolist(), rough):
            if seen[i]:
                continue
            d[~(seen & want)] = np.inf
            near = np.flatnonzero(d <= d.min() + off)
            j = int(near[np.argmin(sq(x[near], x[i]))])
            lists[j], lists[i] = np.append(lists[j], i), np.append(lists[i], j)
            reach(lists, i, inside, seen)
        rest = rest[step:]
        rest = rest[~seen[rest]]


def medoid(x: np.ndarray, rows: np.ndarray) -> int:
    return int(rows[np.argmin(sq(x[rows], x[rows].mean(axis=0)))])


def draw_levels(ids: np.ndarray, degree: int, seed: int) -> np.ndarray:
    """Geometric levels from a hash of the id, so that builds repeat."""
    h = (ids.astype(np.uint64) + np.uint64(seed)) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    u = ((h ^ (h >> np.uint64(32))) >> np.uint64(11)).astype(float) / 2.0**53
    return np.minimum(12, np.floor(-np.log(np.maximum(u, 1e-12)) / np.log(max(2, degree)))).astype(int)


def layered(x: np.ndarray, ids: np.ndarray, degree: int, breadth: int, alpha: float | None, seed: int = 0) -> tuple[np.ndarray, list[list[np.ndarray]]]:
    """Levels, and neighbours by level. alpha None keeps the nearest without pruning."""
    n, level = len(x), draw_levels(ids, degree, seed)
    level[int(np.argmax(level))] = level.max(initial=0)
    nbrs: list[list[np.ndarray]] = [[] for _ in range(n)]
    for at in range(int(level.max(initial=0)) + 1):
        rows = np.flatnonzero(level >= at)
        cap = 2 * degree if at == 0 else degree
        near = knn(x[rows], max(breadth, degree))
        lists = diverse_lists(near, x[rows], degree, alpha) if alpha else [c[:degree] for c in near]
        lists = with_reverse(lists, x[rows], cap, alpha)
        repair(lists, x[rows], int(np.argmax(level[rows])))
        for i, own in zip(rows.tolist(), lists):
            nbrs[i].append(rows[own])
    return level, nbrs


def dense(x: np.ndarray, ids: np.ndarray, degree: int, gamma: int, keep: int, breadth: int) -> tuple[np.ndarray, list[list[np.ndarray]]]:
    """Enlarged lists (degree * gamma), pruned without a look at labels: a neighbour beyond the kept
    prefix goes if one that stays beyond it, which the search expands, has it in its own kept prefix, which nothing prunes."""
    near = knn(x, max(breadth, degree * gamma))
    full = [c[: degree * gamma] for c in near]
    lists = []
    for own in full:
        stays, behind = [], set()
        for j in own[keep:].tolist():
            if j not in behind:
                stays.append(j)
                behind.update(full[j][:keep].tolist())
        lists.append(np.concatenate([own[:keep], stays]).astype(int))
    if len(x):
        repair(lists, x, medoid(x, np.arange(len(x))))
    return np.zeros(len(x), int), [[own] for own in lists]


def shared_label(x: np.ndarray, labels: list[tuple[int, ...]], members: dict[int, np.ndarray], degree: int, breadth: int, alpha: float) -> list[list[np.ndarray]]:
    """Edges only between nodes with a common label: candidates per label, pruned with a look at shared labels."""
    src, dst, sets = [np.zeros(0, int)], [np.zeros(0, int)], label_bits(labels)
    for bits in members.values():
        rows = np.flatnonzero(bits)
        near = knn(x[rows], breadth)
        src.append(np.repeat(rows, [len(c) for c in near]))
        dst.append(rows[np.concatenate(near)])
    lists = diverse_lists(nearest_first(np.concatenate(src), np.concatenate(dst), x), x, degree, alpha, sets)
    lists = with_reverse(lists, x, 2 * degree, alpha, sets)
    for bits in members.values():
        repair(lists, x, medoid(x, np.flatnonzero(bits)), bits)
    return [[own] for own in lists]


def stitched(x: np.ndarray, labels: list[tuple[int, ...]], members: dict[int, np.ndarray], sub_degree: int, breadth: int, stitched_degree: int, alpha: float) -> list[list[np.ndarray]]:
    """One pruned graph for each label, united; nodes with several labels are the bridges; then pruned to stitched_degree."""
    src, dst, sets = [np.zeros(0, int)], [np.zeros(0, int)], label_bits(labels)
    for bits in members.values():
        rows = np.flatnonzero(bits)
        lists = with_reverse(diverse_lists(knn(x[rows], breadth), x[rows], sub_degree, alpha), x[rows], sub_degree, alpha)
        src.append(np.repeat(rows, [len(c) for c in lists]))
        dst.append(rows[np.concatenate(lists)])
    lists = diverse_lists(nearest_first(np.concatenate(src), np.concatenate(dst), x), x, stitched_degree, alpha, sets, stitched_degree)
    for bits in members.values():
        repair(lists, x, medoid(x, np.flatnonzero(bits)), bits)
    return [[own] for own in lists]


SMALL_GROUP = 32


def lattice_edges(groups: Iterable[frozenset[int]]) -> list[tuple[frozenset[int], frozenset[int]]]:
    """Transitively reduced inclusion edges between label sets (parent strictly inside child, nothing between)."""
    found = sorted(groups, key=lambda g: (len(g), sorted(g)))
    by_label: dict[int, list[frozenset[int]]] = {}
    for g in found:
        for a in g:
            by_label.setdefault(a, []).append(g)
    out = []
    for g in found:
        above = [s for s in (min((by_label[a] for a in g), key=len) if g else found) if g < s]
        minimal: list[frozenset[int]] = []
        for s in above:  # rising size
            if not any(m < s for m in minimal):
                minimal.append(s)
        out += [(g, s) for s in minimal]
    return out


def lattice(x: np.ndarray, labels: list[tuple[int, ...]], degree: int, breadth: int, alpha: float, cross: int) -> list[list[np.ndarray]]:
    """Level 0: edges within a group of equal label sets; level 1: edges to near nodes of minimal supersets. An edge implies inclusion."""
    groups: dict[frozenset[int], list[int]] = {}
    for i, own in enumerate(labels):
        groups.setdefault(frozenset(own), []).append(i)
    nbrs: list[list[np.ndarray]] = [[np.zeros(0, int), np.zeros(0, int)] for _ in labels]
    for rows_ in groups.values():
        rows = np.array(rows_)
        if len(rows) <= SMALL_GROUP:
            lists = [np.setdiff1d(np.arange(len(rows)), [i]) for i in range(len(rows))]
        else:
            lists = with_reverse(diverse_lists(knn(x[rows], breadth), x[rows], degree, alpha), x[rows], 2 * degree, alpha)
            repair(lists, x[rows], medoid(x[rows], np.arange(len(rows))))
        for i, own in zip(rows.tolist(), lists):
            nbrs[i][0] = rows[own]
    for parent, child in lattice_edges(groups):
        a, b = np.array(groups[parent]), np.array(groups[child])
        d = (x[a] ** 2).sum(axis=1)[:, None] + (x[b] ** 2).sum(axis=1)[None, :] - 2 * x[a] @ x[b].T
        flat = np.argsort(d, axis=None, kind="stable")[:cross]
        for i, j in zip(*np.unravel_index(flat, d.shape)):
            nbrs[a[i]][1] = np.append(nbrs[a[i]][1], b[j])
    return nbrs


def label_gap(codes: np.ndarray, asked: np.ndarray) -> np.ndarray:
    """Hamming distance of fixed-length label vectors."""
    return (codes != asked).sum(axis=-1)


def fuse(dist: np.ndarray, gap: np.ndarray, m: int, weight: float, additive: bool) -> np.ndarray:
    return dist + weight * gap if additive else dist * (1 + weight * gap / max(1, m))


def fused(x: np.ndarray, labels: list[tuple[int, ...]], k0: int, pool: int, iters: int, sample: int, rev_sample: int, degree: int, diverse_pool: int, diverse_angle: float, label_weight: float, additive: bool = False, start: str = "descent", seed: int = 0) -> list[list[np.ndarray]]:
    """Graph under the fused distance: neighbour descent (or waves of insertions), then edges in diverse directions."""
    n, m = len(x), max((len(a) for a in labels), default=0)
    codes = np.array([list(a) + [-1] * (m - len(a)) for a in labels]).reshape(n, m)
    rng = np.random.default_rng(seed)

    def weights(i: int, c: np.ndarray) -> np.ndarray:
        return fuse(sq(x[c], x[i]), label_gap(codes[c], codes[i]), m, label_weight, additive)

    def best(i: int, c: np.ndarray, k: int) -> np.ndarray:
        c = np.unique(c)
        c = c[c != i]
        return c[np.lexsort((c, weights(i, c)))[:k]]

    norm = (x * x).sum(axis=1)

    def closest(rows: np.ndarray, there: np.ndarray, k: int) -> np.ndarray:
        """rows x there: True for all that may be among the k best, by one matrix product."""
        if k >= len(there):
            return np.ones((len(rows), len(there)), bool)
        gap = np.zeros((len(rows), len(there)), np.int32)
        for j in range(m):
            gap += codes[rows, j][:, None] != codes[there, j][None, :]
        rough = fuse(norm[rows][:, None] + norm[there][None, :] - 2 * x[rows] @ x[there].T, gap, m, label_weight, additive)
        off = 1e-10 * (1 + abs(label_weight)) * (norm[rows] + norm[there].max())
        return rough <= (np.partition(rough, k - 1, axis=1)[:, k - 1] + 2 * off)[:, None]

    if n <= 1:
        return [[np.zeros(0, int)] for _ in range(n)]
    if start == "waves":
        near, done = [np.zeros(0, int)] * n, 0
        order = rng.permutation(n)
        while done < n:  # each wave links to the graph of the waves before it
            wave = order[done : max(done * 2, k0 + 1)]
            there = order[: done or len(wave)]
            for lo in range(0, len(wave), max(1, MATRIX // len(there))):
                some = wave[lo : lo + max(1, MATRIX // len(there))]
                for i, close in zip(some.tolist(), closest(some, there, pool + 1)):
                    near[i] = best(i, there[close], pool)
            done += len(wave)
    else:
        near = [best(i, rng.integers(0, n, k0 + 4), k0) for i in range(n)]
        for _ in range(iters):
            back: list[list[int]] = [[] for _ in range(n)]
            for i, c in enumerate(near):
                for j in c.tolist():
                    if len(back[j]) < rev_sample:
                        back[j].append(i)
            near = [best(i, np.concatenate([c, np.array(back[i], int), *(near[j] for j in c[:sample].tolist())]), pool) for i, c in enumerate(near)]
    cosine = np.cos(np.radians(diverse_angle))
    lists = []
    for i, c in enumerate(near):
        kept: list[int] = []
        rays = x[c[:diverse_pool]] - x[i]
        rays = rays / np.maximum(np.linalg.norm(rays, axis=1), 1e-12)[:, None]
        for j in range(len(rays)):
            if len(kept) < degree and all(rays[r] @ rays[j] < cosine for r in kept):
                kept.append(j)
        lists.append(c[kept])
    lists = with_reverse(lists, x, 2 * degree, None)
    repair(lists, x, medoid(x, np.arange(n)))
    return [[own] for own in lists]


# ------------------------------------------------------------------ searching


def beam(x: np.ndarray, q: np.ndarray, starts: Iterable[int], breadth: int, neighbours: Neighbours, cost: Cost, accept: np.ndarray | None = None, weigh: Callable[[np.ndarray], np.ndarray] | None = None, seen: np.ndarray | None = None) -> list[tuple[float, int]]:
    """Best-first search: (distance, node) of the `breadth` best visited nodes that are accepted, best first."""
    seen = np.zeros(len(x), bool) if seen is None else seen
    weigh = weigh or (lambda c: sq(x[c], q))
    first = np.array(sorted({s for s in starts if not seen[s]}), int)
    if not len(first):
        return []
    seen[first] = True
    cost.dist_comps += len(first)
    todo, best = [], []
    for d, i in zip(weigh(first).tolist(), first.tolist()):
        heapq.heappush(todo, (d, i))
        if accept is None or accept[i]:
            heapq.heappush(best, (-d, -i))
    while len(best) > breadth:
        heapq.heappop(best)
    while todo:
        d, i = heapq.heappop(todo)
        if len(best) >= breadth and d > -best[0][0]:
            break
        cost.hops += 1
        c = neighbours(i)
        c = c[~seen[c]]
        if not len(c):
            continue
        c = np.unique(c)
        seen[c] = True
        cost.dist_comps += len(c)
        for dj, j in zip(weigh(c).tolist(), c.tolist()):
            if len(best) < breadth or dj < -best[0][0]:
                heapq.heappush(todo, (dj, j))
                if accept is None or accept[j]:
                    heapq.heappush(best, (-dj, -j))
                    if len(best) > breadth:
                        heapq.heappop(best)
    return sorted((-d, -i) for d, i in best)


def descend(s: Shard, q: np.ndarray, cost: Cost) -> int:
    """Greedy walk through the upper levels to an entry of level 0."""
    at = int(np.argmax(s.level))
    for level in range(int(s.level[at]), 0, -1):
        found = beam(s.x, q, [at], 1, lambda i, level=level: s.at(i, level), cost)
        at = found[0][1]
    return at


def _restarting(s: Shard, q: np.ndarray, start: int, breadth: int, k: int, allow: np.ndarray, neighbours: Neighbours, cost: Cost, restart: bool = True) -> list[tuple[float, int]]:
    """Beam over passing nodes; if too few were found, starts again (unless restart is off) at passing nodes it hasn't seen."""
    seen = np.zeros(len(s.x), bool)
    best = beam(s.x, q, [start], breadth, neighbours, cost, allow, None, seen)
    want = min(k if breadth < len(s.x) else len(s.x), int(allow.sum()))
    while restart and len(best) < want:
        rest = np.flatnonzero(allow & ~seen)
        if not len(rest):
            break
        cost.rounds += 1
        best = sorted(best + beam(s.x, q, [int(rest[0])], breadth, neighbours, cost, allow, None, seen))[:breadth]
    return best


def search_postfilter(s: Shard, q: np.ndarray, allow: np.ndarray, k: int, l0: int, growth: int, l_max: int, cost: Cost) -> list[tuple[float, int]]:
    """Search without labels, check them, and double the scope until k pass or the limit is reached."""
    start, size, valid = descend(s, q, cost), l0, {}
    while True:
        cost.rounds += 1
        for d, i in beam(s.x, q, [start], size, s.at, cost):
            cost.label_checks += 1
            if allow[i]:
                valid[i] = d
        if len(valid) >= k or size >= min(l_max, len(s.x)):
            return sorted((d, i) for i, d in valid.items())
        size *= growth


def search_twohop(s: Shard, q: np.ndarray, allow: np.ndarray, k: int, breadth: int, cost: Cost, hops: int = 2, restart: bool = True) -> list[tuple[float, int]]:
    """Look at one- and two-hop neighbours, filter, then push."""

    def neighbours(i: int) -> np.ndarray:
        c = s.at(i)
        if hops == 2 and len(c):
            c = np.concatenate([c, *(s.at(j) for j in c.tolist())])
        cost.label_checks += len(c)
        return c[allow[c]]

    return _restarting(s, q, descend(s, q, cost), breadth, k, allow, neighbours, cost, restart)


def search_dense(s: Shard, q: np.ndarray, allow: np.ndarray, k: int, breadth: int, keep: int, degree: int, cost: Cost, scan_below: int = 0, restart: bool = True) -> list[tuple[float, int]]:
    """Walk guided by the filter map; neighbours pruned at build time are recovered through those beyond the kept prefix."""
    rows = np.flatnonzero(allow)
    if len(rows) <= scan_below:
        cost.dist_comps += len(rows)
        return sorted(zip(sq(s.x[rows], q).tolist(), rows.tolist()))[:breadth]

    def neighbours(i: int) -> np.ndarray:
        own = s.at(i)
        c = np.concatenate([own, *(s.at(j) for j in own[keep:].tolist())])
        c = c[np.sort(np.unique(c, return_index=True)[1])]
        cost.label_checks += len(c)
        return c[allow[c]][:degree]

    start = int(rows[0]) if len(rows) else 0
    return _restarting(s, q, start, breadth, k, allow, neighbours, cost, restart)


def search_labelled(s: Shard, q: np.ndarray, allow: np.ndarray, asked: tuple[int, ...], k: int, breadth: int, cost: Cost, multi: bool = True) -> list[tuple[float, int]]:
    """Start at the medoids of the asked labels, stay among nodes with an asked label, check when a node enters the result."""
    used = [a for a in (asked if multi else asked[:1]) if a in s.members]
    if not asked and allow.any():  # nothing to navigate by
        rows = np.flatnonzero(allow)
        cost.dist_comps += len(rows)
        return sorted(zip(sq(s.x[rows], q).tolist(), rows.tolist()))[:breadth]
    if not used:
        return []
    region = np.logical_or.reduce([s.members[a] for a in used])

    def neighbours(i: int) -> np.ndarray:
        c = s.at(i)
        cost.label_checks += len(c)
        return c[region[c]]

    return beam(s.x, q, [s.centre(a) for a in used], breadth, neighbours, cost, allow)


def search_lattice(s: Shard, q: np.ndarray, scenario: str, asked: tuple[int, ...], k: int, breadth: int, cost: Cost) -> list[tuple[float, int]]:
    """Containment: from the minimal groups that hold the asked set along inclusion edges, without label checks.
    Equality: the one group. Overlap: a containment round for each asked label, merged."""
    if scenario in ("equality", "fixed"):
        start = s.groups.get(frozenset(asked))
        return beam(s.x, q, [start], breadth, s.at, cost) if start is not None else []

    def along(i: int) -> np.ndarray:
        return np.concatenate([s.at(i), s.at(i, 1)])

    if scenario == "overlap":
        best: dict[int, float] = {}
        for a in asked:
            cost.rounds += 1
            best |= {i: d for d, i in beam(s.x, q, s.minimal(frozenset([a])), breadth, along, cost)}
        return sorted((d, i) for i, d in best.items())[:breadth]
    return beam(s.x, q, s.minimal(frozenset() if scenario == "nofilter" else frozenset(asked)), breadth, along, cost)


def search_fused(s: Shard, q: np.ndarray, asked: tuple[int, ...], breadth: int, label_weight: float, cost: Cost, additive: bool = False, strict: bool = True) -> list[tuple[float, int]]:
    """Walk under the fused distance; strict drops rows with other labels at the end."""
    m = len(asked)
    codes = s.codes(m)
    want = np.array(asked)

    def weigh(c: np.ndarray) -> np.ndarray:
        return fuse(sq(s.x[c], q), label_gap(codes[c], want), m, label_weight, additive)

    if breadth >= len(s.x):  # nothing is ever cut, so every query visits the same nodes
        seen = s.reached(s.centre())
        cost.dist_comps, cost.hops = cost.dist_comps + len(seen), cost.hops + len(seen)
        rows = s.labelled(s.centre(), asked) if strict else seen
        return sorted(zip((sq(s.x[rows], q) if strict else weigh(rows)).tolist(), rows.tolist()))
    found = beam(s.x, q, [s.centre()], breadth, s.at, cost, None, weigh)
    if strict:
        found = [(d, i) for d, i in found if s.labels[i] == asked]
    return sorted((float(sq(s.x[i : i + 1], q)[0]), i) for _, i in found) if strict else found
