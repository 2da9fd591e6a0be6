"""The operators' registered queries and, where SQL can express one, its DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, bpe, jaccard, langid, license, mixing, packing, quality, substring, urls


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vocabulary(name: str = "byte_bpe_50k.tiktoken") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    weights = urls.train(spark.createDataFrame(urls.LABELLED, "url string, block boolean"))
    return urls.judge(table(spark, sf_dir, "pages"), weights, urls.RULES)


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source", "source_size", "target", "copies", "taken")


def op3_pack_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), vocabulary(), 50256, {"<|endoftext|>": 50256})


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = langid.holdout(F.col("doc_id"))
    seen = docs.where(~held).select(F.col("doc_id").cast("string").alias("key"), "text", "lang")
    found = langid.identify(docs, langid.train(seen))
    return found.select("doc_id", langid.holdout(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "rejected")


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return license.scan(docs, license.fit_idf(docs, license.build_index()))


def op6_nearest_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = ann.fit(table(spark, sf_dir, "embeddings"))
    queries = index.vectors.where("vec_id % 100 = 0").select("vec_id", "v")
    return ann.search(index, queries, 10, ann.calibrate(index, queries, 10))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality.apply_rules(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(table(spark, sf_dir, "documents"), vocabulary(), {"<|endoftext|>": 50256}, keep_ids=False)


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.deduplicate(table(spark, sf_dir, "documents"), digest=True)


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.join_components(table(spark, sf_dir, "documents"), k=3, percent=90).select("doc_id", "n_shingles", "component_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: v for k, v in globals().items() if k.startswith("op") and callable(v)}


_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

SUBSTRING_SQL = f"""with w as (select doc_id, {_WORDS} as words from documents),
win as (select doc_id, i, array_to_string(words[i:i+19], ' ') as key from w, unnest(range(1, greatest(len(words) - 18, 1))) t(i)),
late as (select doc_id, i from (select doc_id, i, min((doc_id, i)) over (partition by key) as f from win) where (doc_id, i) > f),
dead as (select distinct doc_id, i + o as i from late, range(20) r(o)),
kept as (select doc_id, count(*) as n, string_agg(word, ' ' order by i) as t from (select doc_id, unnest(words) as word, generate_subscripts(words, 1) as i from w) x where not exists (select 1 from dead d where d.doc_id = x.doc_id and d.i = x.i) group by 1)
select w.doc_id, len(words)::bigint as n_words, (len(words) - coalesce(n, 0))::bigint as n_removed, sha256(coalesce(t, '')) as kept_sha256 from w left join kept using (doc_id)"""

JACCARD_SQL = f"""with recursive w as (select doc_id, {_WORDS.replace("coalesce(text, '')", _LOWER)} as words from documents),
s as materialized (select distinct doc_id, case when len(words) >= 3 then array_to_string(words[i:i+2], ' ') else array_to_string(words, ' ') end as shingle from w, unnest(range(1, greatest(len(words) - 1, 2))) t(i) where len(words) > 0),
n as materialized (select doc_id, count(*) as n from s group by 1),
p as (select a.doc_id as x, b.doc_id as y, count(*) as c from s a join s b on a.shingle = b.shingle and a.doc_id < b.doc_id group by all),
l as materialized (select x, y from p join n a on a.doc_id = x join n b on b.doc_id = y where 100 * c >= 90 * (a.n + b.n - c)),
e as materialized (select x, y from l union all select y, x from l),
reach as (select doc_id, doc_id as root from n union select e.y, reach.root from reach join e on e.x = reach.doc_id)
select d.doc_id, coalesce(n.n, 0)::bigint as n_shingles, coalesce(r.root, d.doc_id) as component_id from documents d left join n using (doc_id) left join (select doc_id, min(root) as root from reach group by 1) r using (doc_id)"""


def _quality_sql() -> str:
    """The same measures, holdout counts, binomial tails and walk, with the cutoffs of quality.CUTOFFS."""
    blanks = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
    cuts = ", ".join(f"('{r}', {i}, {c})" for r, steps in quality.CUTOFFS.items() for i, c in enumerate(steps))
    shares = {"symbols_per_word": ("n_symbols", "n_words"), "mean_word_chars": ("word_chars", "n_words"), "duplicate_line_share": ("n_dup_lines", "n_lines"), "repeated_word_share": ("n_repeat_words", "n_words")}
    signals = ", ".join(f"(case when {b} > 0 then {a} * 1000000 // {b} else 0 end)::bigint as {r}" for r, (a, b) in shares.items())
    return f"""with w as (select doc_id, lang, coalesce(text, '') as t, {_WORDS} as words, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: length(translate(x, {blanks}, '')) > 0) as lines from documents),
win as (select doc_id, i, array_to_string(words[i:i+4], ' ') as key from w, unnest(range(1, greatest(len(words) - 3, 1))) x(i)),
twice as (select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, key) as c from win) where c > 1),
rep as (select doc_id, count(distinct i + o) as n from twice, range(5) r(o) group by 1),
m as (select w.doc_id, lang, len(words)::bigint as n_words, length(translate(t, {blanks}, ''))::bigint as word_chars, (length(t) - length(translate(t, '#*$%&|<>', '')))::bigint as n_symbols, (len(lines) - len(list_distinct(lines)))::bigint as n_dup_lines, len(lines)::bigint as n_lines, coalesce(rep.n, 0)::bigint as n_repeat_words from w left join rep using (doc_id)),
s as materialized (select *, {signals}, (n_words < 10 or 100 * n_repeat_words > 20 * n_words) as base_failed from m),
u as (unpivot (select doc_id, lang, {", ".join(shares)} from s) on {", ".join(shares)} into name rule value signal),
cuts(rule, step, cutoff) as (values {cuts}),
good as (select s.doc_id, s.lang from s join labels using (doc_id) where quality = 1),
k as (select g.lang, c.rule, c.step, c.cutoff, count(*) as n, count(*) filter (u.signal > c.cutoff) as x from good g join u on u.doc_id = g.doc_id join cuts c on c.rule = u.rule group by all),
t as (select *, case when x <= 0.02 * n then list_sum(list_transform(range(0, x + 1), lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln(0.02) + (n - i) * ln(0.98)))) else 1 end as p from k),
ok as (select *, bool_and(p <= 0.05 / ((select count(distinct coalesce(lang, chr(0))) from good) * {len(shares)})) over (partition by lang, rule order by step) as passed from t),
cut as (select lang, rule, min(cutoff) as cutoff from ok where passed group by all),
bad as (select distinct u.doc_id from u join cut on u.lang is not distinct from cut.lang and u.rule = cut.rule where u.signal > cut.cutoff)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and doc_id not in (select doc_id from bad) as kept from s"""


def oracle_sql() -> dict[str, str]:
    """For queries that SQL expresses; the others are tested against brute-force versions."""
    return {"op7_quality_rules": _quality_sql(), "op9_substring_dedup": SUBSTRING_SQL, "op10_jaccard_join": JACCARD_SQL}
