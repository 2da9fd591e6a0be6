"""Operator 1: URL filter: path rules, then logistic regression on hashed character n-grams.

All of it is DataFrame functions. The model is fitted by stochastic gradient steps over a
small labelled table, folded inside one expression, and is one row of weights that is
broadcast (DIMS doubles). Null urls and urls without `://` have empty host and path and
no n-grams: the intercept alone judges them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise

DIMS = 1024
MAX_LABELLED = 2_000
MAX_RULES = 10_000
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; both empty for null or without `://`."""
    cut = F.instr(url, "://")
    rest = F.when(cut > 0, F.substr(url, cut + 3)).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    return F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), _UPPER, _LOWER), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def ngram_slots(host: Column, path: Column, n: int = 4) -> Column:
    """Slots of the character n-grams of `^host` and path, each repeated as often as it stands."""
    shown = F.concat(F.lit("^"), host, F.lit(" "), F.translate(path, "0123456789", "0000000000"), F.lit("$"))
    last = F.length(shown) - (n - 1)
    return F.when((host == "") & (path == ""), F.array().cast("array<int>")).otherwise(
        F.when(last >= 1, F.transform(F.sequence(F.lit(1), F.greatest(last, F.lit(1))), lambda i: F.pmod(F.xxhash64(F.substr(shown, i, F.lit(n))), F.lit(DIMS)).cast("int"))).otherwise(F.array().cast("array<int>"))
    )


def _margin(w: Column, slots: Column) -> Column:
    size = F.sqrt(F.greatest(F.size(slots), F.lit(1)).cast("double"))
    return w[DIMS] + F.aggregate(slots, F.lit(0.0), lambda s, k: s + w[k]) / size


def train(labelled: DataFrame, epochs: int = 30, rate: float = 0.5, decay: float = 1e-3) -> DataFrame:
    """One row, `weights` array<double> of DIMS + 1 (the last is the intercept), from (url, block boolean).

    labelled holds at most MAX_LABELLED rows, counted before they are gathered. Its order has
    no influence: steps follow the hash of the url. Without rows all weights are zero.
    """
    n = labelled.limit(MAX_LABELLED + 1).count()
    if n > MAX_LABELLED:
        raise ValueError(f"the labelled table has more than {MAX_LABELLED} rows")
    host, path = split_url(F.col("url"))
    rows = labelled.where("block is not null").select(F.xxhash64("url", "block").alias("o"), F.col("block").cast("double").alias("y"), ngram_slots(host, path).alias("x"))
    # a row as a dense vector of scaled counts, so that a step is one zip_with
    gathered = rows.groupBy().agg(F.array_sort(F.collect_list(F.struct("o", "y", "x"))).alias("rows"))
    zero = F.array_repeat(F.lit(0.0), DIMS + 1)

    def dense(x: Column) -> Column:
        size = F.sqrt(F.greatest(F.size(x), F.lit(1)).cast("double"))
        hits = F.array_sort(F.concat(x, F.sequence(F.lit(0), F.lit(DIMS - 1))))
        starts = F.transform(F.sequence(F.lit(0), F.lit(DIMS - 1)), lambda k: F.array_position(hits, k))
        ends = F.concat(F.slice(starts, 2, DIMS - 1), F.array((F.size(hits) + 1).cast("bigint")))
        return F.concat(F.zip_with(starts, ends, lambda a, b: (b - a - 1).cast("double") / size), F.array(F.lit(1.0)))

    # written once, so that the steps below read the vectors and don't derive them again
    vectors = materialise(gathered.select(F.transform("rows", lambda r: F.struct(r["y"].alias("y"), r["x"].alias("x"), dense(r["x"]).alias("v"))).alias("rows")), "urls")

    def step(w: Column, r: Column, eta: Column) -> Column:
        error = 1 / (1 + F.exp(-_margin(w, r["x"]))) - r["y"]
        return F.transform(F.array(error), lambda e: F.zip_with(w, r["v"], lambda a, b: a * (1 - eta * decay) - eta * e * b))[0]

    fitted = vectors.select(
        F.aggregate(
            F.sequence(F.lit(1), F.lit(epochs)), zero, lambda w, t: F.aggregate(F.col("rows"), w, lambda v, r: step(v, r, F.lit(rate) / F.sqrt(t.cast("double"))))
        ).alias("weights")
    )
    return materialise(fitted, "urls")


def parse_rules(rules: list[tuple[str, str]]) -> list[tuple[str, str, str, str]]:
    """(verdict, `host/path`) to (host, path, rule, verdict)."""
    if len(rules) > MAX_RULES:
        raise ValueError(f"more than {MAX_RULES} rules: join them as a table instead")
    return [(r.split("/", 1)[0].lower(), "/" + r.split("/", 1)[1] if "/" in r else "", r, v) for v, r in rules]


def best_rule(host: Column, path: Column, rules: list[tuple[str, str]]) -> Column:
    """The longest rule that fits host and path, as struct(n, rule, verdict); null without one. Ties: the later rule string by code point."""
    by_host: dict[str, list] = {}
    for h, p, r, v in parse_rules(rules):
        by_host.setdefault(h, []).append(F.struct(F.lit(len(r)).alias("n"), F.lit(r).alias("rule"), F.lit(v).alias("verdict"), F.lit(p).alias("path")))
    if not by_host:
        return F.lit(None).cast("struct<n:int,rule:string,verdict:string>")
    table = F.create_map(*[x for h, found in by_host.items() for x in (F.lit(h), F.array(*found))])
    labels = F.split(host, r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    found = F.flatten(F.filter(F.transform(suffixes, lambda s: F.try_element_at(table, s)), lambda x: x.isNotNull()))
    return F.array_max(F.transform(F.filter(found, lambda r: F.startswith(path, r["path"])), lambda r: F.struct(r["n"].alias("n"), r["rule"].alias("rule"), r["verdict"].alias("verdict"))))


def judge(pages: DataFrame, weights: DataFrame, rules: list[tuple[str, str]], threshold: float = 0.6, key: str = "page_id") -> DataFrame:
    """key, host, path, rule, verdict and block_score of every row of pages."""
    host, path = split_url(F.col("url"))
    parts = pages.select(key, host.alias("host"), path.alias("path"))
    # the model is one row of DIMS + 1 doubles: 8 KB
    scored = parts.crossJoin(F.broadcast(weights)).withColumn("slots", ngram_slots(F.col("host"), F.col("path")))
    scored = scored.withColumn("block_score", 1 / (1 + F.exp(-_margin(F.col("weights"), F.col("slots"))))).withColumn("hit", best_rule(F.col("host"), F.col("path"), rules))
    own = F.when(F.col("block_score") > threshold, F.lit("block")).otherwise(F.lit("allow"))
    return scored.select(key, "host", "path", F.col("hit.rule").alias("rule"), F.coalesce("hit.verdict", own).alias("verdict"), "block_score")


# A small labelled URL table (invented addresses; True is block).
LABELLED = [
    ("http://spam-farm.example.org/es/750", True),
    ("https://spam-farm.example.net/en/12?page=2", True),
    ("http://www.spam-farm.example.com/de/8", True),
    ("https://cheap-pills.example.org/en/buy", True),
    ("http://casino-bonus.example.net/win", True),
    ("http://free-casino.example.com/en/spin", True),
    ("https://link-farm.example.org/links/4", True),
    ("http://adult-cams.example.net/live", True),
    ("http://xxx-video.example.com/en/44", True),
    ("https://warez-download.example.org/crack", True),
    ("http://seo-links.example.net/fr/99", True),
    ("http://win-prize.example.com/claim", True),
    ("https://replica-watches.example.net/shop", True),
    ("http://payday-loans.example.org/apply", True),
    ("http://spamblog.example.net/en/3", True),
    ("http://ththre.example.com/fr/825?page=2", False),
    ("https://m.ththth.example.net/en/742/", False),
    ("http://blog.tiontion.example.com/en/214", False),
    ("https://www.ththhe.example.com/en/773", False),
    ("https://blog.tionsh.example.net/en/27", False),
    ("http://www.tionble.example.com/fr/748", False),
    ("https://www.ththwh.example.org/de/511", False),
    ("https://blog.ththan.example.net/es/78", False),
    ("http://news.example.org/en/2020/article", False),
    ("https://university.example.net/de/courses", False),
    ("http://library.example.com/fr/catalogue", False),
    ("https://recipes.example.org/es/soup", False),
    ("http://museum.example.net/en/visit", False),
    ("https://docs.example.com/en/guide.html", False),
    ("http://weather.example.org/fr/paris", False),
]

# Rules of the query, longest wins.
RULES = [("block", "com/en/"), ("allow", "example.com/en/7"), ("allow", "net/de/"), ("block", "example.net/de/8"), ("block", "org/es/")]
