"""Which method supports which constraint, what its build needs, and which to choose.

Method keys: prefilter, quantized, dense, twohop, lattice, postfilter, ivfpq, shared, stitched, fused, two_level.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.carriers import read

CONSTRAINTS = ("containment", "overlap", "equality", "fixed", "combined")

# Supported constraints per method, in the order of CONSTRAINTS; paradigm; labels needed by the build; cheap increments.
METHODS = {
    "prefilter": ("yyyyy", "filter-then-search", True, None),
    "quantized": ("yyyyy", "filter-then-search", False, None),
    "dense": ("yyyyy", "filter-then-search", False, None),
    "twohop": ("yyyyy", "filter-then-search", False, None),
    "lattice": ("yyyyn", "filter-then-search", True, False),
    "postfilter": ("yyyyy", "search-then-filter", False, None),
    "ivfpq": ("yyyyy", "search-then-filter", False, None),
    "shared": ("yyyyy", "hybrid", True, True),
    "stitched": ("yyyyy", "hybrid", True, True),
    "fused": ("nnnyn", "hybrid", True, True),
    "two_level": ("nnnyn", "hybrid", True, False),
}


def supports(method: str, constraint: str) -> bool:
    if constraint == "nofilter":
        return method not in ("fused", "two_level")
    return METHODS[method][0][CONSTRAINTS.index(constraint)] == "y"


def check(method: str, constraint: str) -> None:
    if not supports(method, constraint):
        raise ValueError(f"{method} doesn't support {constraint}")


def _sql(rows: list[tuple], columns: str) -> str:
    def cell(x: object) -> str:
        return "null" if x is None else str(x).lower() if isinstance(x, bool) else f"'{x}'"

    return "select * from (values " + ", ".join("(" + ", ".join(map(cell, r)) + ")" for r in rows) + f") as t({columns})"


def _support_rows() -> list[tuple]:
    return [(m, c, supports(m, c)) for m in METHODS for c in CONSTRAINTS]


def support_matrix(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(_support_rows(), "method string, constraint string, supported boolean")


def _requirement_rows() -> list[tuple]:
    return [(m, p, needs, cheap) for m, (_, p, needs, cheap) in METHODS.items()]


def label_requirement(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(_requirement_rows(), "method string, paradigm string, needs_labels boolean, cheap_increments boolean")


@dataclass(frozen=True)
class Profile:
    """What is known of a workload. selectivity is the passing share; label_length the labels a query asks for."""

    constraint: str
    selectivity: float = 0.1
    label_length: int = 2
    n_labels: int = 100
    k: int = 10
    labels_change: bool = False
    tight_build: bool = False


def recommend(p: Profile) -> list[str]:
    """Methods to try, best first."""
    if p.labels_change or p.tight_build:
        order = ["postfilter", "ivfpq", "twohop"] if p.k == 1 else ["postfilter", "twohop"]
    elif p.constraint == "fixed":
        order = ["lattice", "two_level"]
    elif p.constraint == "combined":
        order = ["prefilter", "dense", "twohop", "postfilter"]
    elif p.constraint == "overlap":
        order = ["stitched", "twohop"]
        if p.k >= 50:
            order = ["shared", "stitched", "dense", "twohop"]
        elif p.n_labels > 100:
            order = ["dense", "twohop", "postfilter"]
        elif p.k == 1:
            order = ["postfilter", "ivfpq", "stitched"]
    else:
        order = ["lattice"]
        if p.selectivity < 0.01 or p.label_length >= 4:
            order = ["lattice", "twohop", "prefilter"]
        elif p.k >= 50:
            order = ["lattice", "dense", "twohop"]
        elif p.k == 1:
            order = ["lattice", "postfilter", "ivfpq"]
    return [m for m in order if supports(m, p.constraint)]


# Situations and the methods advised there.
ADVICE = [
    ("containment", Profile("containment"), "lattice"),
    ("equality", Profile("equality"), "lattice"),
    ("low selectivity", Profile("containment", selectivity=0.001), "lattice,twohop,prefilter"),
    ("long labels", Profile("equality", label_length=5), "lattice,twohop,prefilter"),
    ("fixed length", Profile("fixed"), "lattice,two_level"),
    ("overlap", Profile("overlap"), "stitched,twohop"),
    ("overlap, many labels", Profile("overlap", n_labels=1000), "dense,twohop,postfilter"),
    ("overlap, large k", Profile("overlap", k=100), "shared,stitched,dense,twohop"),
    ("containment, large k", Profile("containment", k=100), "lattice,dense,twohop"),
    ("containment, one neighbour", Profile("containment", k=1), "lattice,postfilter,ivfpq"),
    ("changing labels", Profile("overlap", labels_change=True), "postfilter,twohop"),
    ("combined", Profile("combined"), "prefilter,dense,twohop,postfilter"),
]


def advice_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(s, ",".join(recommend(p))) for s, p, _ in ADVICE], "situation string, methods string")


# The constraint that an event of each type asks for, when events stand for a log of search requests.
REQUESTED = {"click": "containment", "error": "equality", "purchase": "overlap", "signup": "fixed", "view": "combined"}
# What is advised for a constraint at k = 1, 10 and 100.
ADVISED = {
    "containment": ("lattice,postfilter,ivfpq", "lattice", "lattice,dense,twohop"),
    "equality": ("lattice,postfilter,ivfpq", "lattice", "lattice,dense,twohop"),
    "overlap": ("postfilter,ivfpq,stitched", "stitched,twohop", "shared,stitched,dense,twohop"),
    "fixed": ("lattice,two_level",) * 3,
    "combined": ("prefilter,dense,twohop,postfilter",) * 3,
}


def requests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """constraint, k, requests: events counted as a log of searches. A value below 20 asks for one neighbour, below 100 (or none) for 10, else for 100; other types ask nothing."""
    asked = F.create_map(*(F.lit(x) for pair in REQUESTED.items() for x in pair))[F.col("event_type")]
    k = F.when(F.col("value") < 20, 1).when(F.col("value") >= 100, 100).otherwise(10)
    return read(spark, sf_dir, "events").select(asked.alias("constraint"), k.alias("k")).where("constraint is not null").groupBy("constraint", "k").agg(F.count("*").alias("requests"))


def requests_supported(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The support matrix, with the number of logged requests that each cell stands for."""
    logged = requests(spark, sf_dir).groupBy("constraint").agg(F.sum("requests").alias("requests"))
    return support_matrix(spark).join(logged, "constraint", "left").select("method", "constraint", "supported", F.coalesce("requests", F.lit(0)).alias("requests"))


def requests_advised(spark: SparkSession, sf_dir: str) -> DataFrame:
    """constraint, k, requests, methods: what is advised for the requests in the log."""
    rules = [(c, k, ",".join(recommend(Profile(c, k=k)))) for c in CONSTRAINTS for k in (1, 10, 100)]
    return requests(spark, sf_dir).join(F.broadcast(spark.createDataFrame(rules, "constraint string, k int, methods string")), ["constraint", "k"])


SUPPORT_SQL = _sql(_support_rows(), 'method, "constraint", supported')
REQUIREMENT_SQL = _sql(_requirement_rows(), "method, paradigm, needs_labels, cheap_increments")
ADVICE_SQL = _sql([(s, want) for s, _, want in ADVICE], "situation, methods")
_LOG_SQL = (
    "select case event_type " + " ".join(f"when '{t}' then '{c}'" for t, c in REQUESTED.items()) + " end as \"constraint\", "
    "(case when value < 20 then 1 when value >= 100 then 100 else 10 end)::int as k, count(*) as requests from events group by 1, 2 having \"constraint\" is not null"
)
REQUESTS_SQL = f"select method, \"constraint\", supported, coalesce(requests, 0)::bigint as requests from ({SUPPORT_SQL}) left join (select \"constraint\", sum(requests) as requests from ({_LOG_SQL}) group by 1) using (\"constraint\")"
ADVISED_SQL = f"select \"constraint\", k, requests, methods from ({_LOG_SQL}) join (" + _sql([(c, k, m) for c, own in ADVISED.items() for k, m in zip((1, 10, 100), own)], '"constraint", k_, methods').replace("select *", 'select "constraint", k_::int as k, methods') + ") using (\"constraint\", k)"
