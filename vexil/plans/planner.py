"""From a request to a plan: check what the method supports, choose the route, write the DataFrame."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import Constraint, assert_fixed_length, constraint
from ..operators import exact, graph, ivf, quantize, two_level
from ..sources.carriers import assert_vectors
from . import advisor


@dataclass(frozen=True)
class SearchPlan:
    method: str
    constraint: str
    k: int
    route: str
    scope: int  # first scope of widening methods, from the expected share of passing rows


class FilteredSearch:
    """One entry for all methods: fit once, search with any constraint that the method supports."""

    def __init__(self, base: DataFrame, method: str = "prefilter", **build):
        self.base, self.method, self.dims = base, method, assert_vectors(base)
        if method == "quantized":
            self.index = quantize.fit(base, **build)
        elif method == "ivfpq":
            self.index = ivf.fit(base, **build)
        elif method == "two_level":
            assert_fixed_length(base)
            self.index = two_level.fit(base, **build)
        elif method in graph.DEFAULTS:
            if method == "fused":
                assert_fixed_length(base)
            params = {k: build.pop(k) for k in list(build) if k in graph.DEFAULTS[method]}
            self.index = graph.fit(base, method, params, **build)
        elif method != "prefilter":
            raise ValueError(f"no method {method}")

    def resolve(self, of: str | Constraint, k: int, share: float | None = None) -> SearchPlan:
        name = constraint(of).name
        advisor.check(self.method, name)
        route = {"equality": "group", "fixed": "group", "containment": "posting", "overlap": "posting", "nofilter": "block"}.get(name, "column")
        scope = max(k, int(k / share)) if share else 4 * k
        return SearchPlan(self.method, name, k, route, scope)

    def search(self, queries: DataFrame, of: str | Constraint, k: int = 10, share: float | None = None, **settings) -> DataFrame:
        """qid, rank, id, dist, written as one logical plan."""
        dims = queries.select(F.size("qvec").alias("d")).distinct().limit(2).collect()
        if dims and self.dims is not None and [r.d for r in dims] != [self.dims]:
            raise ValueError("queries and base differ in dimensions")
        plan = self.resolve(of, k, share)
        if self.method == "prefilter":
            return exact.search(self.base, queries, of, k, settings.get("route", plan.route))
        if self.method == "quantized":
            return quantize.search(self.index, queries, of, k, **settings)
        if self.method == "ivfpq":
            return ivf.search(self.index, queries, of, k, **settings)
        if self.method == "two_level":
            return two_level.search(self.index, queries, k, **settings)
        settings.setdefault("l0" if self.method == "postfilter" else "breadth", plan.scope)
        return graph.search(self.index, queries, of, k, self.base, **settings)


def union_of_runs(search: FilteredSearch, queries: DataFrame, parts: list[str | Constraint], k: int, **settings) -> DataFrame:
    """Fallback for a disjunction on a method without combined predicates: one run for each part, merged."""
    found = search.search(queries, parts[0], k, **settings)
    for p in parts[1:]:
        found = found.unionByName(search.search(queries, p, k, **settings))
    return exact.top_k(found.select("qid", "id", "dist").distinct(), k)
