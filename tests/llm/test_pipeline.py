"""The pipeline's stages on whole small tables, each against what it must keep and drop."""

from collections import Counter

from pyspark.sql import functions as F

import corpus_pipeline as cp
from vexil.llm import common, jaccard
from vexil.llm.common import materialise

from .test_operators import corpus, docs_frame, plain_components, plain_substring


def one_of_each(rows):
    """The smallest id of each component; documents without words, or without an id, are their own."""
    return [i for (i, n, c), times in plain_components(rows, 5, 80).items() for _ in range(times) if i is None or n == 0] + sorted({c for i, n, c in plain_components(rows, 5, 80) if n and c is not None})


def test_texts_of_one_id_in_two_components(spark, sf):
    """Near copies go by text: of the texts of an id, only those go that are linked with something smaller."""
    a, q = (" ".join(f"{x}{i}" for i in range(300)) for x in "aq")
    rows = [(7, a), (7, q), (9, a + " more"), (3, q + " more"), (11, a), (11, a), (12, "own words here"), (12, "own words here"), (13, ""), (13, ""), (None, a), (None, a)]
    docs = docs_frame(spark, [(i, t, "en", "s") for i, t in rows])
    kept = Counter((r.doc_id, r.text) for r in cp.drop_near_copies(spark, docs, sf).collect())
    assert kept == Counter({(7, a): 1, (3, q + " more"): 1, (12, "own words here"): 1, (13, ""): 2, (None, a): 2})


def test_stages_leave_only_what_they_read(spark, sf):
    """A stage's scratch is gone when it returns; what its result reads stays."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for stage in (cp.drop_near_copies, cp.cut_repeats):
        before = {path for _, path in common._tables}
        out = stage(spark, docs, sf)
        left = {path for _, path in common._tables} - before
        assert len(left) == 1
        assert out.count() > 0


def test_rounds_of_block_pairs_lose_no_link(spark, monkeypatch):
    """Many small rounds, blocks of a few nodes, and sets sent again only to groups of several blocks: the same components as by brute force."""
    held, plain = [], jaccard.materialise
    monkeypatch.setattr(jaccard, "BLOCK_NODES", 3)
    monkeypatch.setattr(jaccard, "ROUND_ITEMS", 1)
    monkeypatch.setattr(jaccard, "materialise", lambda df, tag, batch=None: held.append(tag) or plain(df, tag, batch))
    words = [f"w{i}" for i in range(120)]
    # ten near copies of each of six texts that overlap, so that groups have several components and blocks
    rows = [(10 * g + v, " ".join(words[8 * g : 8 * g + 60] + [f"x{g}{v}"] * (v % 4))) for g in range(6) for v in range(10)]
    found = jaccard.join_components(docs_frame(spark, [(i, t, "en", "s") for i, t in rows]), 3, 80)
    want = {i: c for (i, _, c) in plain_components(rows, 3, 80)}
    assert {r.doc_id: r.component_id for r in found.collect()} == want
    assert "held" in held


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    sizes = {}
    for name, stage in cp.STAGES:
        out = materialise(stage(spark, docs, sf), "test")
        if name != "bpe":
            assert out.columns == docs.columns and dict(out.dtypes) == dict(docs.dtypes)
        rows = [(r.doc_id, r.text) for r in docs.collect()]
        kept = [r.doc_id for r in out.collect()]
        sizes[name] = len(kept)
        if name == "language_id":
            assert len(kept) >= 0.97 * len(rows)
        if name == "jaccard_join":
            assert sorted(kept) == sorted(one_of_each(rows))
        if name == "substring_dedup":
            want = Counter({(i, n - gone): c for (i, n, gone, _), c in plain_substring(rows, 20).items()})
            assert Counter((r.doc_id, len(r.text.encode().split())) for r in out.collect()) == want
            assert out.where("n_chars != length(text)").count() == 0
        if name == "mix_sources":
            assert max(Counter(kept).values()) <= 3
        docs = out
    assert docs.count() == sizes["mix_sources"]


def test_edges(spark, sf):
    docs = docs_frame(spark, corpus())
    for _, stage in cp.STAGES[:-1]:
        assert stage(spark, docs, sf).columns == docs.columns
        assert stage(spark, docs.limit(0), sf).count() == 0
    mixed = cp.mix_sources(spark, docs, sf)
    assert mixed.where("doc_id = 901").count() == 1  # empty texts are kept once
    assert cp.identify_language(spark, docs, sf).where(F.col("doc_id").isin(900, 901, 902)).count() == 0
