"""Each operator against a brute-force version on small fixtures: nulls, empty and long texts, ties, repeats, empty tables."""

import hashlib
import math
import random
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from vexil.llm import ann, bpe, jaccard, langid, license, mixing, packing, quality, substring, urls
from vexil.llm.queries import vocabulary

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, node string, cuts int"


def docs_frame(spark, rows):
    """(doc_id, text, lang, source) with extra columns whose names the operators use inside."""
    return spark.createDataFrame([(i, t, la, s, len(t or ""), "x", 1) for i, t, la, s in rows], DOCS)


def corpus(seed=1, n=60):
    rng = random.Random(seed)
    words = ["alpha", "beta", "Gamma", "the", "of", "und", "é", "x1", "ça", "don't", "#tag", "naïve"] + [f"w{i}" for i in range(400)]
    passage = " ".join(rng.choices(words, k=70))
    out = [(None, "null id text " * 9, "en", "a"), (900, None, None, None), (901, "", "en", "a"), (902, " \t\n\x0b", "en", "b"), (903, "one", "de", "b"), (904, "two words", "de", None)]
    for i in range(n):
        text = " ".join(rng.choices(words, k=rng.randint(3, 160)))
        if i % 5 == 0:
            text = text[: len(text) // 2] + " " + passage + "\n" + text[len(text) // 2 :]
        if i % 7 == 0:
            text = text + "\n" + text
        out.append((i, text, rng.choice(["en", "de", None]), rng.choice(["a", "b", "c", None])))
    base = out[-1][1]
    out += [(500, base, "en", "a"), (501, base + " tail", "en", "a"), (502, base.upper(), "en", "b"), (500, base, "en", "a"), (700, "a " * 3000, "en", "c")]
    # one id with two texts: a copy of another document, and one that is near to a third or to none
    for far, near in (("a", "z"), ("b", "q")):
        own, other = ([f"{x}{i}" for i in range(60)] for x in (far, near))
        out += [(800 + ord(far), " ".join(own[:30]), "en", "a"), (810 + ord(far), " ".join(own[:30]), "en", "b"), (810 + ord(far), " ".join(other), "de", "b"), (820 + ord(far), " ".join(other + ["tail"]), "de", None)]
    return out


# ------------------------------------------------------------------ 1


def test_url_parts_and_rules(spark):
    cases = [("HTTP://Ex.Example.COM/en/7a?x#y", "ex.example.com", "/en/7a", "example.com/en/7", "allow"), ("x://a.net/de/8", "a.net", "/de/8", "net/de/", "allow"), ("x://example.net/de/8", "example.net", "/de/8", "example.net/de/8", "block"), ("x://notexample.net/de/8", "notexample.net", "/de/8", "net/de/", "allow"), ("http://b.com/en/", "b.com", "/en/", "com/en/", "block"), ("http://com/en/", "com", "/en/", "com/en/", "block"), (None, "", "", None, None), ("no scheme", "", "", None, None), ("a://?q", "", "", None, None), ("a://ÄB.org#z", "Äb.org", "", None, None), ("u://h.org/es/x\n?", "h.org", "/es/x\n", "org/es/", "block")]
    weights = urls.train(spark.createDataFrame(urls.LABELLED, "url string, block boolean"))
    pages = spark.createDataFrame([(i, c[0], 1.0) for i, c in enumerate(cases)], "page_id bigint, url string, weights double").drop("weights")
    got = {r.page_id: r for r in urls.judge(pages, weights, urls.RULES).collect()}
    for i, (_, host, path, rule, verdict) in enumerate(cases):
        assert (got[i].host, got[i].path, got[i].rule) == (host, path, rule)
        assert verdict is None or got[i].verdict == verdict


def test_url_model_learns_and_matches_python(spark):
    table = spark.createDataFrame(urls.LABELLED, "url string, block boolean")
    weights = urls.train(table)
    w = weights.first().weights
    host, path = urls.split_url(F.col("url"))
    rows = table.select("url", "block", urls.ngram_slots(host, path).alias("x"), F.xxhash64("url", "block").alias("o")).orderBy("o", "block").collect()
    v = np.zeros(urls.DIMS + 1)
    for t in range(1, 31):
        for r in rows:
            x = np.zeros(urls.DIMS + 1)
            np.add.at(x, r.x, 1 / math.sqrt(max(1, len(r.x))))
            x[-1] = 1
            eta = 0.5 / math.sqrt(t)
            v = v * (1 - eta * 1e-3) - eta * (1 / (1 + math.exp(-(v @ x))) - r.block) * x
    assert np.allclose(v, w, atol=1e-9)
    assert set(weights.collect()[0].weights) != {0.0}
    judged = urls.judge(table.select(F.col("url").alias("page_id"), "url"), weights, []).collect()
    truth = dict(urls.LABELLED)
    assert sum((r.verdict == "block") == truth[r.page_id] for r in judged) >= 0.9 * len(truth)
    with pytest.raises(ValueError):
        urls.train(spark.range(urls.MAX_LABELLED + 1).selectExpr("cast(id as string) url", "true block"))
    assert set(urls.train(table.limit(0)).first().weights) == {0.0}
    assert urls.judge(spark.createDataFrame([], "page_id bigint, url string"), weights, urls.RULES).count() == 0


# ------------------------------------------------------------------ 2


def expected_targets(sizes):
    order = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: i % 3 + 1 for i, s in enumerate(order)}
    capped, total = {}, sum(sizes.values())
    while True:
        left, w = total - sum(capped.values()), sum(weight[s] for s in order if s not in capped)
        over = [s for s in order if s not in capped and left * weight[s] / w > 3 * sizes[s]]
        if not over:
            return {s: capped.get(s, left * weight[s] / w if w else 0.0) for s in order}
        capped |= {s: 3 * sizes[s] for s in over}


@pytest.mark.parametrize("residual", ["words", "copies"])
def test_mixing_hits_targets(spark, residual):
    rows = corpus()
    got = mixing.mix(docs_frame(spark, rows), residual=residual).collect()
    assert len(got) == len(rows)
    again = mixing.mix(docs_frame(spark, rows).repartition(3), residual=residual).collect()
    assert sorted(map(repr, got)) == sorted(map(repr, again))
    words = lambda t: len((t or "").encode().split())
    sizes = defaultdict(int)
    for _, t, _, s in rows:
        sizes[s] += words(t)
    want, taken = expected_targets(sizes), Counter()
    for r in got:
        assert r.source_size == sizes[r.source] and abs(r.target - want[r.source]) < 1e-6
        assert r.taken == r.copies * r.size + r.extra <= 3 * r.size and r.taken >= 0
        taken[r.source] += r.taken
    longest = max(words(t) for _, t, _, _ in rows)
    for s in sizes:
        assert abs(taken[s] - want[s]) <= (1 if residual == "words" else longest)


def test_mixing_is_unbiased_and_handles_caps(spark):
    rows = [(i, "w " * (i % 7 + 1), "en", "b" if i < 300 else "a") for i in range(310)]
    first = {r.doc_id: r for r in mixing.mix(docs_frame(spark, rows)).collect()}
    assert first[309].target == pytest.approx(3 * first[309].source_size)
    assert {r.copies for r in first.values() if r.source == "a"} == {3}
    means = np.mean([[r.copies for r in sorted(mixing.mix(docs_frame(spark, rows), seed=s).collect(), key=lambda r: r.doc_id)][:300] for s in range(4)], axis=0)
    assert abs(means.mean() - first[0].target / first[0].source_size) < 0.05
    assert mixing.mix(docs_frame(spark, [])).count() == 0


# ------------------------------------------------------------------ 3


def test_best_fit_decreasing_matches_a_plain_search():
    rng = random.Random(4)
    for _ in range(40):
        width = rng.randint(4, 60)
        lengths = sorted((rng.randint(1, width) for _ in range(rng.randint(0, 80))), reverse=True)
        rooms = []
        for n in lengths:
            fit = [r for r in rooms if r >= n]
            if fit:
                rooms.remove(min(fit))
                rooms.append(min(fit) - n)
            else:
                rooms.append(width - n)
        rows = packing.best_fit_decreasing(lengths, width)
        assert sorted(width - sum(lengths[i] for i in r) for r in rows) == sorted(rooms)
        assert sorted(i for r in rows for i in r) == list(range(len(lengths)))


def test_packing_is_lossless(spark, tmp_path):
    rows = corpus()
    packed = packing.pack_documents(docs_frame(spark, rows), vocabulary(), width=64, shard_tokens=2_000)
    parts = defaultdict(list)
    for r in packed.collect():
        ids = np.frombuffer(r.ids, "<u2")
        assert len(ids) == 64 and r.cu_seqlens[-1] == r.n_tokens and (ids[r.n_tokens :] == 50256).all() and r.position_resets == r.cu_seqlens[:-1]
        pos = packing.positions(r.cu_seqlens, 64)
        assert all(pos[a] == 0 and pos[b - 1] == b - a - 1 for a, b in zip(r.cu_seqlens[:-1], r.cu_seqlens[1:]))
        for doc, k, a, b in zip(r.doc_ids, r.segments, r.cu_seqlens[:-1], r.cu_seqlens[1:]):
            parts[doc].append((k, ids[a:b].tolist()))
    encoder = bpe.TreeEncoder(vocabulary())
    for doc in {i for i, *_ in rows}:
        texts = [t or "" for i, t, _, _ in rows if i == doc]
        ids = [x for _, p in sorted(parts[doc]) for x in p]
        if len(texts) == 1:
            assert ids[-1] == 50256 and encoder.decode(ids[:-1]) == texts[0]
        else:
            assert len(ids) == sum(len(encoder.encode(t)) + 1 for t in texts)
    packing.write_matrices(packed, f"{tmp_path}/m")
    assert spark.read.parquet(f"{tmp_path}/m").count() == packed.count()
    assert packing.pack_documents(docs_frame(spark, []), vocabulary()).count() == 0


def test_packing_of_wide_ids(spark):
    """Ids over 16 bits come back whole."""
    texts = {1: [70_000, 5, 99_999], 2: list(range(65_530, 65_545)), 3: []}
    encoded = spark.createDataFrame([(i, np.array([*x, 1], "<u4").tobytes()) for i, x in texts.items()], "doc_id bigint, ids binary")
    got = defaultdict(list)
    for r in packing.pack(encoded, width=8, pad=0, bits=32).collect():
        ids = np.frombuffer(r.ids, "<u4")
        for doc, k, lo, hi in zip(r.doc_ids, r.segments, r.cu_seqlens[:-1], r.cu_seqlens[1:]):
            got[doc].append((k, ids[lo:hi].tolist()))
    assert {i: [x for _, part in sorted(parts) for x in part] for i, parts in got.items()} == {i: [*x, 1] for i, x in texts.items()}
    with pytest.raises(ValueError):
        packing.pack(encoded, bits=8)


# ------------------------------------------------------------------ 4


def test_language_on_held_out_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    held = langid.holdout(F.col("doc_id"))
    model = langid.train(docs.where(~held).select(F.col("doc_id").cast("string").alias("key"), "text", "lang"))
    found = langid.identify(docs.where(held), model).join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert found and sum(r.lang == r.lang_pred for r in found) >= 0.95 * len(found)
    assert all(0 <= r.score <= 1 for r in found)
    assert sum(r.rejected for r in found) <= 0.02 * len(found)


def test_language_edges(spark):
    rows = corpus()
    docs = docs_frame(spark, rows)
    model = langid.train(docs.select(F.col("doc_id").cast("string").alias("key"), "text", "lang"))
    got = langid.identify(docs, model, keep=True)
    assert got.columns[: len(docs.columns)] == docs.columns
    bare = {r.doc_id: r for r in got.collect()}
    for i in (900, 901, 902):
        assert (bare[i].lang_pred, bare[i].lang_score, bare[i].rejected) == ("und", 0.0, True)
    digits = langid.identify(docs_frame(spark, [(1, "123 ½ Ⅷ ²", "en", "a")]), model).first()
    assert digits.lang_pred == "und"
    empty = langid.train(docs.limit(0).select(F.col("doc_id").cast("string").alias("key"), "text", "lang"))
    assert {r.lang_pred for r in langid.identify(docs, empty).collect()} == {"und"}
    assert langid.identify(docs.limit(0), model).count() == 0


# ------------------------------------------------------------------ 5


def test_license_places_match_a_plain_search(spark):
    rows = corpus() + [(800, "Released under the MIT License. Under The MIT license; under-the-mit-license!", "en", "a"), (801, "Licensed under CC BY-NC 4.0.", "en", "a"), (802, "the mit license under Apache License, Version 2.0 apache license version 20", "en", "a"), (803, "This work is licensed under the GNU General Public License, version 3.", "en", "a"), (804, "under theé mit license", "en", "a")]
    index = license.fit_idf(docs_frame(spark, rows), license.build_index())
    got = {(r.doc_id, r.n_words): r for r in license.scan(docs_frame(spark, rows), index).collect()}
    for doc, text, _, _ in rows:
        words = license.words_of((text or "").encode())
        places, labels = [], set()
        for label, phrase in license.BASE_PHRASES.items():
            p = license.words_of(phrase.encode())
            hits = [i for i in range(len(words)) if words[i : i + len(p)] == p]
            places += hits
            labels |= {label} if hits else set()
        r = got[(doc, len(words))]
        assert (r.n_base, r.first_word, r.last_word) == (len(places), min(places, default=None), max(places, default=None))
        assert r.base_labels == ",".join(sorted(labels)) and labels <= set(r.labels.split(","))
        assert 0 <= r.score <= 1
    assert got[(803, 12)].labels == "gpl-3" and got[(801, 7)].base_labels == "cc-by-nc"
    assert license.scan(docs_frame(spark, []), index).count() == 0


def test_license_notices_do_not_displace_each_other(spark):
    notices = [n for _, n, _ in license.NOTICES]
    prose = " ".join("the person may copy in binary or source forms and use the terms subject to version 2 or 3 in the public domain".split() * 40)
    rng = random.Random(4)
    files = [" and ".join(rng.sample(notices, n)) for n in (1, 2, 3, 5, 8) for _ in range(6)] + [f"{a} x {notices[0]}" for a in notices] + [f"{prose} {a} {prose}" for a in notices]
    files += [notices[0].replace("granted", "granted indeed"), " ".join(notices[0].split()[2:])]
    rows = [(i, t, "en", "a") for i, t in enumerate(files)]
    index = license.fit_idf(docs_frame(spark, rows), license.build_index())
    got = {r.doc_id: r for r in license.scan(docs_frame(spark, rows), index).collect()}
    for doc, text, _, _ in rows:
        words, labels, score = license.words_of(text.encode()), set(), 0.0
        for own in index.templates:
            for start in range(-len(own.words), len(words) + 1):
                if all(any(words[i : i + len(key)] == key for i in range(max(0, start + p - 2), start + p + 3)) for p, key in own.keys):
                    share = sum(0 <= start + p < len(words) and words[start + p] == w for p, w in enumerate(own.words)) / len(own.words)
                    if share >= 0.6 and (not own.base or share == 1):
                        labels, score = labels | {own.label}, max(score, share)
        assert (got[doc].labels, got[doc].score) == (",".join(sorted(labels)), score)


# ------------------------------------------------------------------ 6


def test_nearest_vectors_recall_and_edges(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(1500, 24))
    x[700:900] = x[700]  # many copies
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    rows += [(2000, None), (2001, [0.0] * 24), (2002, [float("nan")] * 24), (2003, [None] + [1.0] * 23), (2004, [1.0] * 3), (5, x[5].tolist()), (2005, [float("inf")] * 24)]
    index = ann.fit(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>"), lists=8)
    assert index.n == 1500
    queries = index.vectors.where("vec_id % 50 = 0").select("vec_id", "v")
    truth = {q: sorted((float(np.sqrt(((x[i] - x[q]) ** 2).sum())), i) for i in range(1500) if i != q)[:10] for q in range(0, 1500, 50)}
    exact = defaultdict(list)
    for r in ann.exact(index, queries).orderBy("query_id", "rank").collect():
        exact[r.query_id].append((r.score, r.vec_id))
    assert {q: [i for _, i in t] for q, t in truth.items()} == {q: [i for _, i in t] for q, t in exact.items()}
    found = ann.search(index, queries, 10, ann.calibrate(index, queries))
    assert ann.recall(found, ann.exact(index, queries)) >= 0.9
    assert all(r.query_id != r.vec_id for r in found.collect())
    tiny = ann.fit(spark.createDataFrame(rows[:4], "vec_id bigint, embedding array<double>"))
    assert ann.search(tiny, tiny.vectors.select("vec_id", "v"), 10).count() == 12
    none = ann.fit(spark.createDataFrame([], "vec_id bigint, embedding array<double>"))
    assert ann.search(none, none.vectors.select("vec_id", "v"), 10, ann.calibrate(none, none.vectors.select("vec_id", "v"))).count() == 0


def test_nearest_vectors_fill_k_from_small_lists(spark):
    rng = np.random.default_rng(5)
    x = np.repeat(rng.normal(size=(12, 8)) * 50, 5, axis=0) + rng.normal(size=(60, 8)) * np.repeat(np.arange(12) % 2, 5)[:, None]  # tight groups, half of them equal vectors
    index = ann.fit(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, embedding array<double>"), lists=24)
    assert (index.sizes == 0).any() and index.sizes.sum() == 60
    queries = index.vectors.select("vec_id", "v")
    for k, want in ((10, 10), (59, 59), (80, 59)):
        assert Counter(r.query_id for r in ann.search(index, queries, k, 1).collect()) == dict.fromkeys(range(60), want)


def test_scan_abandons_candidates_and_keeps_recall(spark, sf):
    """The hypothesis tests give up most candidates of the probed lists, and the neighbours stay."""
    vectors = spark.read.parquet(sf.replace("sf0.001", "sf0.1") + "/embeddings.parquet")
    index = ann.fit(vectors)
    queries = index.vectors.where("vec_id % 100 = 0").select("vec_id", "v")
    probes = ann.calibrate(index, queries, 10)
    counts = ann.scan_counts(index, queries, 10, probes).selectExpr("sum(candidates) as c", "sum(abandoned) as a", "count(*) as n").first()
    assert counts.n == queries.count() and counts.a > 0.2 * counts.c
    assert ann.scan_counts(index, queries, 10, probes, 0.0).where("abandoned > 0").count() == 0
    everything = {r.vec_id: np.array(r.v) for r in index.vectors.collect()}
    ids = np.array(sorted(everything))
    x = np.stack([everything[i] for i in ids])
    found = ann.search(index, queries, 10, probes).collect()
    hits = sum(r.vec_id in truth[r.query_id] for truth in [{q: set(ids[ids != q][np.argsort(((x[ids != q] - everything[q]) ** 2).sum(axis=1), kind="stable")[:10]]) for q in ids if q % 100 == 0}] for r in found)
    assert hits >= 0.9 * len(found) and len(found) == 10 * counts.n


# ------------------------------------------------------------------ 7


def plain_quality(text):
    words = (text or "").encode().split()
    words = [w.decode() for w in words]
    windows = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    seen = Counter(windows)
    hit = {i + j for i, w in enumerate(windows) if seen[w] > 1 for j in range(5)}
    lines, earlier, dup = (text or "").split("\n"), set(), 0
    for line in lines:
        if line.strip(" \t\n\x0b\x0c\r"):
            dup += line in earlier
            earlier.add(line)
    return len(words), sum(map(len, words)), sum((text or "").count(c) for c in "#*$%&|<>"), dup, len(hit)


def test_quality_measures_match_plain_python(spark):
    rows = corpus() + [(810, "a b c d e a b c d e\n#$%\n#$%\n \n \n", "en", "a"), (811, "x x x x x x x", None, "a"), (812, "\U0001f642 é|é <b>", "fr", "a")]
    labels = spark.createDataFrame([(i, i % 2, None) for i in range(60)] + [(None, 1, 0), (5000, 1, 0), (3, None, 0)], "doc_id bigint, quality int, toxic int")
    got = quality.apply_rules(docs_frame(spark, rows), labels).collect()
    assert len(got) == len(rows)
    texts = defaultdict(list)
    for i, t, _, _ in rows:
        texts[i].append(plain_quality(t))
    for r in got:
        own = (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words)
        assert own in texts[r.doc_id]
        assert r.base_failed == (r.n_words < 10 or 100 * r.n_repeat_words > 20 * r.n_words)
        assert not (r.base_failed and r.kept)
    assert quality.apply_rules(docs_frame(spark, []), labels.limit(0)).count() == 0


def test_binomial_tail_is_exact(spark):
    cases = [(n, x) for n in (1, 5, 40, 300, 5000) for x in (0, 1, 3, 7, 90) if x <= 0.02 * n] + [(10, 9)]
    got = spark.createDataFrame(cases, "n int, x int").select("n", "x", quality.binomial_tail(F.col("n").cast("double"), F.col("x").cast("double"), 0.02).alias("p")).collect()
    for r in got:
        want = sum(math.comb(r.n, i) * 0.02**i * 0.98 ** (r.n - i) for i in range(r.x + 1)) if r.x <= 0.02 * r.n else 1.0
        assert r.p == pytest.approx(want, rel=1e-6)


def test_certified_rules_limit_false_rejections(spark):
    rows = [("en", 0, 6_000_000, 0, 0)] * 990 + [("en", 4_000_000, 6_000_000, 0, 0)] * 10 + [("de", 4_000_000, 6_000_000, 0, 0)] * 50
    holdout = spark.createDataFrame(rows, "lang string, symbols_per_word bigint, mean_word_chars bigint, duplicate_line_share bigint, repeated_word_share bigint")
    cut = {(r.lang, r.rule): r.cutoff for r in quality.certify(holdout, 0.02, 0.05).collect()}
    tail = sum(math.comb(1000, i) * 0.02**i * 0.98 ** (1000 - i) for i in range(11))
    assert (("en", "symbols_per_word") in cut) == (tail <= 0.05 / 8)
    assert cut[("en", "repeated_word_share")] == min(quality.CUTOFFS["repeated_word_share"])
    assert not any(lang == "de" for lang, _ in cut)  # too few labels


# ------------------------------------------------------------------ 8


def test_bpe_equals_the_library(spark):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    rng = random.Random(2)
    alphabet = ["a", "b", "th", "e ", "  ", "\n", "'s", "'", "!", "é", "日本", "🙂", " ", "\x1c", "\x85", "<|endoftext|>", "<|endo", "text|>", "1", "²", "\u0301", "'ll", "\t", "x" * 30]
    encoder = bpe.TreeEncoder(vocabulary(), {"<|endoftext|>": 50256}, leaf_chars=40, piece_bytes=16)
    texts = ["".join(rng.choices(alphabet, k=rng.randint(0, 120))) for _ in range(400)] + ["".join(rng.choices("abcdeth", k=3000)), " " * 500 + "x", "\n" * 333, "é" * 900, "1" * 700, "'" * 300 + "s"]
    for t in texts:
        assert encoder.encode(t) == library.encode(t, add_special_tokens=False).ids
        assert encoder.decode(encoder.encode(t)) == t
    rows = corpus()
    got = bpe.encode_documents(docs_frame(spark, rows), vocabulary(), {"<|endoftext|>": 50256}).collect()
    want = Counter()
    for i, t, _, _ in rows:
        ids = library.encode(t or "", add_special_tokens=False).ids
        want[(i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest())] += 1
    assert Counter((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in got) == want


# ------------------------------------------------------------------ 9


def plain_substring(rows, length):
    first = {}
    for i, t, *_ in sorted((r for r in rows if r[0] is not None), key=lambda r: r[0]):
        w = (t or "").encode().split()
        for s in range(len(w) - length + 1):
            key = tuple(w[s : s + length])
            first[key] = min(first.get(key, (i, s)), (i, s))
    out = Counter()
    for i, t, *_ in rows:
        w = (t or "").encode().split()
        dead = set()
        for s in range(len(w) - length + 1) if i is not None else ():
            if first[tuple(w[s : s + length])] < (i, s):
                dead |= set(range(s, s + length))
        kept = b" ".join(x for j, x in enumerate(w) if j not in dead)
        out[(i, len(w), len(dead), hashlib.sha256(kept).hexdigest())] += 1
    return out


@pytest.mark.parametrize("length", [20, 7])
def test_substring_equals_brute_force(spark, length):
    rows = corpus()
    got = substring.deduplicate(docs_frame(spark, rows), length, digest=True).collect()
    assert Counter((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in got) == plain_substring(rows, length)
    docs = docs_frame(spark, rows)
    texts = substring.deduplicate(docs, length)
    assert texts.columns == docs.columns and texts.count() == len(rows)
    assert {r.doc_id: r.text for r in texts.collect() if r.doc_id == 903} == {903: "one"}
    assert substring.deduplicate(docs.limit(0), length, digest=True).count() == 0


# ------------------------------------------------------------------ 10


def plain_components(rows, k, percent):
    sets = []
    for i, t, *_ in rows:
        w = (t or "").encode().lower().split()
        sets.append((i, frozenset(tuple(w[j : j + k]) for j in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])))
    root = list(range(len(sets)))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for a in range(len(sets)):
        for b in range(a):
            x, y = sets[a][1], sets[b][1]
            if x and y and sets[a][0] is not None and sets[b][0] is not None and 100 * len(x & y) >= percent * len(x | y):
                root[max(find(a), find(b))] = min(find(a), find(b))
    least = defaultdict(list)
    for a, (i, _) in enumerate(sets):
        if i is not None:
            least[find(a)].append(i)
    return Counter((i, len(s), None if i is None else min(least[find(a)])) for a, (i, s) in enumerate(sets))


def edited(rng, words, share):
    return [rng.choice(["edit", "other", f"n{rng.randint(0, 999)}"]) if rng.random() < share else w for w in words]


@pytest.mark.parametrize(("k", "percent", "merged"), [(3, 90, None), (5, 80, None), (3, 90, {b: frozenset(range(0, 400, 2)) for b in range(40)}), (5, 80, {b: frozenset(range(0, 400, 4)) for b in range(40)})])
def test_components_equal_brute_force(spark, k, percent, merged):
    rng = random.Random(8)
    rows = corpus(seed=3, n=30)
    common = [f"p{i}" for i in range(60)]
    for i in range(150):  # texts around shared passages, and near copies with a growing number of edits
        own = [f"q{rng.randint(0, 300)}" for _ in range(rng.randint(3, 140))]
        rows.append((1000 + 10 * i, " ".join(own + common * (i % 3 == 0)), "en", "a"))
        for j in range(i % 6):
            rows.append((1001 + 10 * i + j, " ".join(edited(rng, own + common * (i % 3 == 0), 0.006 * j)), "en", "a"))
    got = jaccard.join_components(docs_frame(spark, rows), k, percent, merged).collect()
    assert Counter((r.doc_id, r.n_shingles, r.component_id) for r in got) == plain_components(rows, k, percent)


def test_bands_guarantee(spark):
    for percent in (80, 90, 95):
        bands = jaccard.Bands(percent)
        for n in range(1, 400):
            own = bands.of(n)
            for other in range(n, int(n * 100 / percent) + 1):
                shared = set(own) & set(bands.of(other))
                assert shared
                gap = (n + other) * (100 - percent) // (100 + percent)
                assert any(gap <= bands.differ(b) for b in shared)
    with pytest.raises(ValueError):
        jaccard.Bands(50)
    assert jaccard.join_components(docs_frame(spark, [])).count() == 0


def test_each_link_between_two_families_counts(spark):
    """Pairs of nodes that are one family without being linked, all in one large cell; two links join members of the first two families."""
    links = {(100, 102), (101, 103)}
    keys = defaultdict(set)
    for node in range(100, 110):
        keys[node] |= {f"own{node // 2}-{i}" for i in range(8)} | {f"all{i}" for i in range(8)}
    for i in range(8):  # the centres of the keys that all have; they share one key with each other, so no family
        keys[i] |= {f"all{i}"} | {f"few{min(i, j)}-{max(i, j)}" for j in range(8) if j != i}
    ids = {k: at for at, k in enumerate(sorted(set().union(*keys.values())))}
    members = spark.createDataFrame([(ids[k], node, 40, 8, 9 if node < 8 else 5) for node, own in keys.items() for k in own], "key bigint, node bigint, n int, need int, pop bigint")
    twin = {b: a for a, b in links}
    items = {node: np.arange(40, dtype=np.uint64) + np.uint64(1000 * twin.get(node, node)) for node in keys}
    sets = spark.createDataFrame([(node, len(x), x.tobytes()) for node, x in items.items()], "node bigint, n bigint, items binary")
    comp = {r.node: r.comp for r in jaccard.link_nodes(members, sets, 90).collect()}
    joined = {(a, b) for a in keys for b in keys if a < b and comp.get(a, a) == comp.get(b, b)}
    assert joined == links


def test_texts_that_share_an_id_keep_their_own_sets(spark):
    texts = [" ".join(f"{side}{i}" for i in range(50)) for side in "ab"]
    docs = docs_frame(spark, [(7, t, "en", "a") for t in texts] + [(8, texts[0], "en", "a")])
    node = {t: jaccard.node_hash(s) for t, s in zip(texts, jaccard.shingle_sets([t.encode() for t in texts], 3))}
    wanted = spark.createDataFrame([(7, n) for n in node.values()], "doc_id bigint, node bigint")
    got = {r.node: np.frombuffer(r.items, np.uint64) for r in jaccard._node_sets(docs.repartition(1), wanted, 3).collect()}
    assert set(got) == set(node.values())
    assert all(jaccard.node_hash(s) == n for n, s in got.items())


def test_sets_of_a_large_group_meet_by_size(spark, monkeypatch):
    """Sets that their sizes keep apart aren't sent to one block; those whose sizes just allow a link are found, whatever class they fall into."""
    monkeypatch.setattr(jaccard, "BLOCK_NODES", 4)
    real, sent = jaccard.materialise, []

    def counted(df, tag, *more):
        out = real(df, tag, *more)
        if tag == "visits":
            sent.append(out.selectExpr("sum(size(met)) as s").first().s if "met" in out.columns else out.count())
        return out

    monkeypatch.setattr(jaccard, "materialise", counted)
    small = [4 * x for x in (1, 2, 4, 5, 8, 10, 16, 20, 25, 32, 50, 64, 80, 100, 125, 128, 160, 200, 250, 256)]
    sizes = [n for m in small for n in (m, m * 5 // 4)]  # 80 % of the larger one are the smaller one
    items = [np.arange(n, dtype=np.uint64) + np.uint64(10_000 * (i // 2)) for i, n in enumerate(sizes)]
    groups = spark.createDataFrame([(7, i, i, n) for i, n in enumerate(sizes)], "family bigint, node bigint, comp bigint, n int")
    sets = spark.createDataFrame([(i, len(x), x.tobytes()) for i, x in enumerate(items)], "node bigint, n bigint, items binary")
    links = {tuple(sorted((r.a, r.b))) for r in jaccard._block_links(groups, sets, 80).collect()}
    assert links == {(i, i + 1) for i in range(0, len(sizes), 2)}
    assert sum(sent) < 4 * len(sizes)
