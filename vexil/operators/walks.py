"""The searches of `kernels` for many queries of one shard at once. No Spark in here.

Each query takes the hops that it takes there, in the same order, and finds the same rows at the same cost. Queries advance
together: one round is a hop of each, whose neighbours are looked up, checked and measured in one go.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from heapq import heappop, heappush

import numpy as np

from . import kernels
from .kernels import Cost, Shard, sq

Found = list[tuple[float, int]]
Neighbours = Callable[[np.ndarray, np.ndarray], tuple[np.ndarray, np.ndarray]]  # queries, nodes: which of them, neighbour

TOGETHER = 256  # queries that advance together at most
SEEN = 1 << 21  # queries times nodes of a shard, as each query may visit and queue every node
KEPT = 1 << 20  # queries times breadth
WIDE = 16  # a walk that likely expands this part of its shard has all distances measured at once


@dataclass
class Links:
    """The neighbour lists of all nodes in one array."""

    at: np.ndarray
    to: np.ndarray

    @classmethod
    def of(cls, lists: list[np.ndarray]) -> Links:
        return cls(np.concatenate([[0], np.cumsum([len(c) for c in lists])]).astype(np.int64), np.concatenate([np.zeros(0, np.int64), *lists]).astype(np.int64))

    def __call__(self, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each neighbour of the nodes: the position of its node, and itself; in order."""
        first = self.at[nodes]
        size = self.at[nodes + 1] - first
        whose = np.repeat(np.arange(len(nodes)), size)
        return whose, self.to[np.arange(len(whose)) + np.repeat(first - np.cumsum(size) + size, size)]


def links(s: Shard, level: int = 0) -> Links:
    if ("links", level) not in s.starts:
        s.starts["links", level] = Links.of([s.at(i, level) for i in range(len(s.x))])
    return s.starts["links", level]


class Block:
    """Queries of one shard that are answered together."""

    def __init__(self, s: Shard, q: np.ndarray, asked: list[tuple[int, ...]]):
        self.s, self.q, self.asked, n = s, q, asked, len(q)
        self.dist_comps, self.hops, self.label_checks, self.rounds = (np.zeros(n, np.int64) for _ in range(4))
        kinds = {a: i for i, a in enumerate(dict.fromkeys(asked))}
        self.kinds, self.kind = list(kinds), np.array([kinds[a] for a in asked], np.int64)

    def costs(self) -> list[Cost]:
        return [Cost(*map(int, c)) for c in zip(self.dist_comps, self.hops, self.label_checks, self.rounds)]

    def far(self, who: np.ndarray, c: np.ndarray) -> np.ndarray:
        return sq(self.s.x[c], self.q[who])


def beams(block: Block, who: np.ndarray, starts: list[list[int]], breadth: int, near: Neighbours, accept: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None, weigh: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None, seen: np.ndarray | None = None) -> list[Found]:
    """kernels.beam for the queries `who` of the block. seen: a line for each of them, which is carried on."""
    n, out = len(block.s.x), []
    step = max(1, min(TOGETHER, SEEN // max(1, n), KEPT // max(1, min(n, breadth))))
    for lo in range(0, len(who), step):
        some = who[lo : lo + step]
        out += _beams(block, some, starts[lo : lo + step], breadth, near, accept, weigh or block.far, np.zeros((len(some), n), bool) if seen is None else seen[lo : lo + step])
    return out


def _beams(block: Block, who: np.ndarray, starts: list[list[int]], breadth: int, near: Neighbours, accept, weigh, seen: np.ndarray) -> list[Found]:
    n = seen.shape[1]
    todo: list[list] = [[] for _ in who]
    best: list[list] = [[] for _ in who]

    def visit(walk: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """What of the neighbours c of each walk is new, in order of nodes, and its distances; and whether it is accepted."""
        new = ~seen[walk, c]
        key = np.unique(walk[new] * n + c[new])
        walk = key // n
        c = key - walk * n
        seen[walk, c] = True
        block.dist_comps[who] += np.bincount(walk, minlength=len(who))
        return walk, c, weigh(who[walk], c), np.ones(len(c), bool) if accept is None else accept(who[walk], c)

    first = [(b, i) for b, own in enumerate(starts) for i in own]
    if not first:
        return best
    walk, c, d, ok = visit(*np.array(first, np.int64).T)
    for b, i, di, good in zip(walk.tolist(), c.tolist(), d.tolist(), ok.tolist()):
        heappush(todo[b], (di, i))
        if good:
            heappush(best[b], (-di, -i))
    for own in best:
        while len(own) > breadth:
            heappop(own)
    active = [b for b, t in enumerate(todo) if t]
    while active:
        walks, nodes, edge = [], [], []
        for b in active:
            if todo[b]:
                d, i = heappop(todo[b])
                own = best[b]
                full = len(own) >= breadth
                if not full or d <= -own[0][0]:
                    walks.append(b)
                    nodes.append(i)
                    edge.append(-own[0][0] if full else np.inf)
        active = walks
        if not walks:
            break
        at = np.array(walks)
        block.hops[who[at]] += 1
        whose, c = near(who[at], np.array(nodes))
        edges = np.zeros(len(who))
        edges[at] = edge
        walk, c, d, ok = visit(at[whose], c)
        may = np.flatnonzero(d < edges[walk])  # a walk's edge only comes closer
        for b, di, i, good in zip(walk[may].tolist(), d[may].tolist(), c[may].tolist(), ok[may].tolist()):
            own = best[b]
            if len(own) < breadth or di < -own[0][0]:
                heappush(todo[b], (di, i))
                if good:
                    heappush(own, (-di, -i))
                    if len(own) > breadth:
                        heappop(own)
    return [sorted((-d, -i) for d, i in own) for own in best]


class Ranks:
    """A shard's nodes in order of their distance from one query: where a walk sees much of the shard, it compares whole numbers."""

    def __init__(self, s: Shard, q: np.ndarray):
        self.dist = sq(s.x, q)
        order = np.argsort(self.dist, kind="stable")
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        self.node, self.rank = order.tolist(), rank.tolist()
        self.first = self.last = range(len(order))  # the ranks of equal distances
        new = np.flatnonzero(np.diff(self.dist[order]) > 0) + 1
        if len(new) + 1 < len(order):
            edges = np.concatenate([[0], new, [len(order)]])
            self.first, self.last = (np.repeat(x, np.diff(edges)).tolist() for x in (edges[:-1], edges[1:] - 1))

    def beam(self, starts: list[int], breadth: int, lists: list[list[int]], seen: bytearray, accept: bytes | None = None) -> tuple[Found, int, list[int]]:
        """kernels.beam; also how many nodes were visited, and which were expanded. What stands as seen is not entered."""
        rank, node, n = self.rank, self.node, len(self.node)
        todo, best, popped = [], [], []
        first = sorted({i for i in starts if not seen[i]})
        visited = len(first)
        for i in first:
            seen[i] = 1
            heappush(todo, rank[i])
            if accept is None or accept[i]:
                heappush(best, -rank[i])
        while len(best) > breadth:
            heappop(best)
        full = len(best) >= breadth > 0
        low, high = (self.first[-best[0]], self.last[-best[0]]) if full else (n, n)
        while todo:
            r = heappop(todo)
            if r > high:
                break
            popped.append(node[r])
            for j in lists[node[r]]:
                if not seen[j]:
                    seen[j] = 1
                    visited += 1
                    r = rank[j]
                    if r < low:
                        heappush(todo, r)
                        if accept is None or accept[j]:
                            heappush(best, -r)
                            if len(best) > breadth:
                                heappop(best)
                            if len(best) == breadth:
                                low, high = self.first[-best[0]], self.last[-best[0]]
        rows = [node[-r] for r in sorted(best, reverse=True)]
        return list(zip(self.dist[rows].tolist(), rows)), visited, popped


def sorted_lists(s: Shard) -> list[list[int]]:
    if "sorted" not in s.starts:
        s.starts["sorted"] = [np.unique(s.at(i)).tolist() for i in range(len(s.x))]
    return s.starts["sorted"]


def plain(links: Links) -> Neighbours:
    return lambda who, nodes: links(nodes)


def descend(block: Block) -> list[list[int]]:
    """Greedy walks through the upper levels to the entries of level 0."""
    s, everyone = block.s, np.arange(len(block.q))
    top = int(np.argmax(s.level))
    at = [[top]] * len(everyone)
    for level in range(int(s.level[top]), 0, -1):
        at = [[found[0][1]] for found in beams(block, everyone, at, 1, plain(links(s, level)))]
    return at


def _restarting(block: Block, starts: list[list[int]], breadth: int, k: int, allow: Allow, near: Neighbours, restart: bool, who: np.ndarray) -> list[Found]:
    n, out = len(block.s.x), []
    step = max(1, min(TOGETHER, SEEN // max(1, n)))
    for lo in range(0, len(who), step):
        own = who[lo : lo + step]
        seen = np.zeros((len(own), n), bool)
        best = beams(block, own, starts[lo : lo + step], breadth, near, allow.of, None, seen)
        want = [min(k if breadth < n else n, int(allow.row(i).sum())) for i in own.tolist()]
        lack = np.array([b for b in range(len(own)) if restart and len(best[b]) < want[b]], np.int64)
        while len(lack):
            rest = [np.flatnonzero(allow.row(i) & ~seen[b]) for b, i in zip(lack.tolist(), own[lack].tolist())]
            some = [j for j, r in enumerate(rest) if len(r)]
            lack = lack[some]
            if not len(lack):
                break
            block.rounds[own[lack]] += 1
            lines = seen[lack]
            more = beams(block, own[lack], [[int(rest[j][0])] for j in some], breadth, near, allow.of, None, lines)
            seen[lack] = lines
            for b, found in zip(lack.tolist(), more):
                best[b] = sorted(best[b] + found)[:breadth]
            lack = np.array([b for b in lack.tolist() if len(best[b]) < want[b]], np.int64)
        out += best
    return out


class Allow:
    """Filter maps: one for each distinct set of asked labels, or one for each query where they are given."""

    def __init__(self, block: Block, scenario: str, allowed: list | None):
        if allowed is None:
            self.maps, self.which = [block.s.allow(scenario, a) for a in block.kinds], block.kind
        else:
            self.maps, self.which = [np.isin(block.s.ids, np.asarray(a, np.int64)) for a in allowed], np.arange(len(allowed))
        self.maps = np.stack(self.maps)

    def of(self, who: np.ndarray, c: np.ndarray) -> np.ndarray:
        return self.maps[self.which[who], c]

    def row(self, i: int) -> np.ndarray:
        return self.maps[self.which[i]]


def search_postfilter(block: Block, allow: Allow, k: int, l0: int, growth: int, l_max: int) -> list[Found]:
    starts, size, n = descend(block), l0, len(block.s.x)
    valid: list[dict[int, float]] = [{} for _ in block.q]
    wide = np.array([WIDE * max(l0, k * n / max(1, allow.row(i).sum())) >= n for i in range(len(block.q))])

    def more(i: int, size: int, found: Found) -> bool:
        """Takes what a round found; whether another is needed."""
        block.label_checks[i] += len(found)
        passes = allow.row(i)
        valid[i].update((j, d) for d, j in found if passes[j])
        return len(valid[i]) < k and size < min(l_max, n)

    for i in np.flatnonzero(wide).tolist():
        ranks, own = Ranks(block.s, block.q[i]), l0
        while True:
            found, visited, popped = ranks.beam(starts[i], own, sorted_lists(block.s), bytearray(n))
            block.rounds[i] += 1
            block.dist_comps[i] += visited
            block.hops[i] += len(popped)
            if not more(i, own, found):
                break
            own *= growth
    who = np.flatnonzero(~wide)
    while len(who):
        block.rounds[who] += 1
        answers = beams(block, who, [starts[i] for i in who.tolist()], size, plain(links(block.s)))
        who = np.array([i for i, found in zip(who.tolist(), answers) if more(i, size, found)], np.int64)
        size *= growth
    return [sorted((d, i) for i, d in own.items()) for own in valid]


def search_twohop(block: Block, allow: Allow, k: int, breadth: int, hops: int, restart: bool) -> list[Found]:
    own = links(block.s)

    def near(who: np.ndarray, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        whose, c = own(nodes)
        if hops == 2:
            through, further = own(c)
            whose, c = np.concatenate([whose, whose[through]]), np.concatenate([c, further])
        block.label_checks[who] += np.bincount(whose, minlength=len(who))
        passes = allow.of(who[whose], c)
        return whose[passes], c[passes]

    return _restarting(block, descend(block), breadth, k, allow, near, restart, np.arange(len(block.q)))


def search_dense(block: Block, allow: Allow, k: int, breadth: int, keep: int, degree: int, scan_below: int, restart: bool) -> list[Found]:
    s = block.s
    wide = s.starts.setdefault(("wide", keep), {})  # node -> its neighbours and theirs, worked out when a walk comes by

    def around(i: int) -> np.ndarray:
        if i not in wide:
            own = s.at(i)
            c = np.concatenate([own, *(s.at(j) for j in own[keep:].tolist())])
            wide[i] = c[np.sort(np.unique(c, return_index=True)[1])]
        return wide[i]

    def near(who: np.ndarray, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        lists = [around(i) for i in nodes.tolist()]
        size = np.array([len(c) for c in lists])
        block.label_checks[who] += size
        whose, c = np.repeat(np.arange(len(who)), size), np.concatenate(lists)
        passes = allow.of(who[whose], c)
        whose, c = whose[passes], c[passes]
        first = np.arange(len(whose)) - np.searchsorted(whose, np.arange(len(who)))[whose] < degree
        return whose[first], c[first]

    out: list[Found] = [[] for _ in block.q]
    who, starts = [], []
    for i, q in enumerate(block.q):
        rows = np.flatnonzero(allow.row(i))
        if len(rows) <= scan_below:
            block.dist_comps[i] += len(rows)
            out[i] = sorted(zip(sq(s.x[rows], q).tolist(), rows.tolist()))[:breadth]
        else:
            who.append(i)
            starts.append([int(rows[0]) if len(rows) else 0])
    for i, found in zip(who, _restarting(block, starts, breadth, k, allow, near, restart, np.array(who, np.int64))):
        out[i] = found
    return out


def search_labelled(block: Block, allow: Allow, k: int, breadth: int, multi: bool) -> list[Found]:
    s, n = block.s, len(block.s.x)
    used = [[a for a in (asked if multi else asked[:1]) if a in s.members] for asked in block.kinds]
    region = np.stack([np.logical_or.reduce([s.members[a] for a in own]) if own else np.zeros(n, bool) for own in used])
    own = links(s)

    def near(who: np.ndarray, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        whose, c = own(nodes)
        block.label_checks[who] += np.bincount(whose, minlength=len(who))
        inside = region[block.kind[who[whose]], c]
        return whose[inside], c[inside]

    out: list[Found] = [[] for _ in block.q]
    who, shut, degree = [], {}, np.diff(own.at)
    for i, asked in enumerate(block.asked):
        kind = block.kind[i]
        if not asked and allow.row(i).any():  # nothing to navigate by
            rows = np.flatnonzero(allow.row(i))
            block.dist_comps[i] += len(rows)
            out[i] = sorted(zip(sq(s.x[rows], block.q[i]).tolist(), rows.tolist()))[:breadth]
        elif used[kind] and WIDE * breadth * region[kind].sum() >= n * allow.row(i).sum():
            if kind not in shut:
                shut[kind] = bytearray((~region[kind]).tobytes())
            out[i], visited, popped = Ranks(s, block.q[i]).beam([s.centre(a) for a in used[kind]], breadth, sorted_lists(s), bytearray(shut[kind]), allow.row(i).tobytes())
            block.dist_comps[i] += visited
            block.hops[i] += len(popped)
            block.label_checks[i] += int(degree[popped].sum())
        elif used[kind]:
            who.append(i)
    starts = [[s.centre(a) for a in used[block.kind[i]]] for i in who]
    for i, found in zip(who, beams(block, np.array(who, np.int64), starts, breadth, near, allow.of)):
        out[i] = found
    return out


def search_lattice(block: Block, scenario: str, k: int, breadth: int) -> list[Found]:
    s, everyone = block.s, np.arange(len(block.q))
    if scenario in ("equality", "fixed"):
        starts = [s.groups.get(frozenset(asked)) for asked in block.asked]
        return beams(block, everyone, [[] if i is None else [i] for i in starts], breadth, plain(links(s)))
    if "along" not in s.starts:
        s.starts["along"] = Links.of([np.concatenate([s.at(i), s.at(i, 1)]) for i in range(len(s.x))])
    along = plain(s.starts["along"])
    if scenario != "overlap":
        return beams(block, everyone, [s.minimal(frozenset() if scenario == "nofilter" else frozenset(asked)) for asked in block.asked], breadth, along)
    best: list[dict[int, float]] = [{} for _ in block.q]
    for turn in range(max((len(asked) for asked in block.asked), default=0)):
        who = np.array([i for i, asked in enumerate(block.asked) if len(asked) > turn], np.int64)
        block.rounds[who] += 1
        for i, found in zip(who.tolist(), beams(block, who, [s.minimal(frozenset([block.asked[i][turn]])) for i in who.tolist()], breadth, along)):
            best[i].update((j, d) for d, j in found)
    return [sorted((d, i) for i, d in own.items())[:breadth] for own in best]


def search_fused(block: Block, breadth: int, label_weight: float, additive: bool, strict: bool) -> list[Found]:
    s, out = block.s, [[] for _ in block.q]
    for m in sorted({len(asked) for asked in block.asked}):
        who = np.array([i for i, asked in enumerate(block.asked) if len(asked) == m], np.int64)
        codes, want = s.codes(m), np.array([a if len(a) == m else (0,) * m for a in block.asked], np.int64).reshape(len(block.q), m)

        def weigh(of: np.ndarray, c: np.ndarray) -> np.ndarray:
            return kernels.fuse(block.far(of, c), kernels.label_gap(codes[c], want[of]), m, label_weight, additive)  # noqa: B023

        if breadth >= len(s.x):  # every query visits the same nodes
            for i in who.tolist():
                cost = Cost()
                out[i] = kernels.search_fused(s, block.q[i], block.asked[i], breadth, label_weight, cost, additive, strict)
                block.dist_comps[i], block.hops[i] = cost.dist_comps, cost.hops
            continue
        for i, found in zip(who.tolist(), beams(block, who, [[s.centre()]] * len(who), breadth, plain(links(s)), None, weigh)):
            rows = np.array([j for _, j in found if not strict or s.labels[j] == block.asked[i]], np.int64)
            out[i] = sorted(zip(sq(s.x[rows], block.q[i]).tolist(), rows.tolist())) if strict else found
    return out


def search(method: str, p: dict, s: Shard, scenario: str, q: np.ndarray, asked: list[tuple[int, ...]], allowed: list | None, k: int, breadth: int, settings: dict) -> tuple[list[Found], list[Cost]]:
    """What each query finds in the shard, best first, and its costs."""
    block = Block(s, q, asked)
    get = settings.get
    if method == "lattice":
        found = search_lattice(block, scenario, k, breadth)
    elif method == "fused":
        found = search_fused(block, breadth, p["label_weight"], bool(get("additive", False)), bool(get("strict", True)))
    else:
        allow = Allow(block, scenario, allowed)
        if method == "postfilter":
            found = search_postfilter(block, allow, k, int(get("l0") or breadth), int(get("growth", 2)), int(get("l_max") or len(s.ids)))
        elif method == "twohop":
            found = search_twohop(block, allow, k, breadth, int(get("hops", 2)), bool(get("restart", True)))
        elif method == "dense":
            found = search_dense(block, allow, k, breadth, int(p["keep"]), int(get("fan") or p["degree"] * p["gamma"]), int(get("scan_below", 0)), bool(get("restart", True)))
        else:
            found = search_labelled(block, allow, k, breadth, bool(get("multi", True)))
    return found, block.costs()
