"""Operator 5: licence scan with a positional rare-token index.

Templates (notices and short phrases) are cut into words; the index maps a word to
the templates whose key phrases have it as their rarest word (highest IDF; document
frequencies are counted over all documents). Where that word stands within its whole key
phrase, all starts that have the phrase near its place are proposed and verified: every
mandatory key phrase of the template has to stand near its place. The score is the share of
the template's words found where they should be. Each template proposes its starts on its own,
so the other notices and words of a file take none away; IDF moves cost only.
Base phrases are templates that are their own key phrase: all of their places are found.

Words: A-Z lower-cased, maximal runs of digits, letters and non-ASCII characters.
Null text is empty. Ties between templates keep both; repeated rows are scanned one by one.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import as_bytes

_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def words_of(text: bytes) -> list[bytes]:
    return text.translate(_TABLE).split()


# Labels and phrases that the scan must find, each word for word.
BASE_PHRASES = {
    "mit": "under the mit license",
    "apache-2": "apache license version 2",
    "cc-by-nc": "cc by nc",
}

# Short public licence notices (label, notice, mandatory key phrases).
NOTICES = [
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ["permission is hereby granted free of charge"]),
    ("mit", "released under the mit license", ["mit license"]),
    ("apache-2", "licensed under the apache license version 2 0", ["apache license"]),
    ("gpl-3", "this work is licensed under the gnu general public license version 3", ["gnu general public license", "version 3"]),
    ("gpl-2", "this work is licensed under the gnu general public license version 2", ["gnu general public license", "version 2"]),
    ("lgpl", "licensed under the gnu lesser general public license", ["gnu lesser general public license"]),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", ["redistribution and use in source and binary forms"]),
    ("mpl-2", "subject to the terms of the mozilla public license v 2 0", ["mozilla public license"]),
    ("cc-by-nc", "licensed under cc by nc 4 0", ["cc by nc"]),
    ("cc-by-sa", "licensed under cc by sa 4 0", ["cc by sa"]),
    ("cc0", "dedicated to the public domain under cc0 1 0 universal", ["cc0", "public domain"]),
    ("proprietary", "all rights reserved", ["all rights reserved"]),
]


@dataclass
class Template:
    label: str
    words: list[bytes]
    keys: list[tuple[int, list[bytes]]]
    base: bool
    anchor: int = 0  # position of the rarest word of the key phrases
    place: int = 0  # position of the key phrase that has it
    key: list[bytes] = field(default_factory=list)


@dataclass
class LicenceIndex:
    templates: list[Template]
    idf: dict[bytes, float] = field(default_factory=dict)
    postings: dict[bytes, list[int]] = field(default_factory=dict)

    def fit(self, n_docs: int, df: dict[bytes, int]) -> LicenceIndex:
        vocabulary = {w for t in self.templates for w in t.words}
        self.idf = {w: math.log((1 + n_docs) / (1 + df.get(w, 0))) for w in vocabulary}
        self.postings = defaultdict(list)
        for i, t in enumerate(self.templates):
            spots = [(p + o, p, key) for p, key in t.keys for o in range(len(key))]
            t.anchor, t.place, t.key = max(spots, key=lambda x: (self.idf[t.words[x[0]]], -x[0]))
            self.postings[t.words[t.anchor]].append(i)
        return self


def build_index(base: dict[str, str] | None = None, notices: list[tuple[str, str, list[str]]] | None = None) -> LicenceIndex:
    found = []
    for label, phrase in (BASE_PHRASES if base is None else base).items():
        w = words_of(phrase.encode())
        found.append(Template(label, w, [(0, w)], True))
    for label, notice, keys in NOTICES if notices is None else notices:
        w = words_of(notice.encode())
        places = []
        for key in keys:
            k = words_of(key.encode())
            places.append((next(i for i in range(len(w)) if w[i : i + len(k)] == k), k))
        found.append(Template(label, w, places, False))
    return LicenceIndex(found).fit(0, {})


def scan_text(words: list[bytes], index: LicenceIndex, shift: int = 2) -> tuple[list[tuple[int, int]], dict[int, float]]:
    """Places (template, start) of base phrases, and the score of each template found."""
    spots: dict[bytes, list[int]] = defaultdict(list)
    for i in [i for i, w in enumerate(words) if w in index.postings]:
        spots[words[i]].append(i)
    places, scores = [], {}
    for w, found in spots.items():
        for t in index.postings[w]:
            own = index.templates[t]
            back = own.anchor - own.place
            starts = [at - own.anchor for at in found if at >= back and words[at - back : at - back + len(own.key)] == own.key]
            if own.base:
                places += [(t, start) for start in starts]
                scores |= {t: 1.0} if starts else {}
                continue
            for start in (s + d for s in starts for d in range(-shift, shift + 1)):
                if scores.get(t) == 1.0:
                    break
                if all(_near(words, start + p, key, shift) for p, key in own.keys):
                    hits = sum(0 <= start + p < len(words) and words[start + p] == w for p, w in enumerate(own.words))
                    scores[t] = max(scores.get(t, 0.0), hits / len(own.words))
    return places, scores


def _near(words: list[bytes], at: int, key: list[bytes], shift: int) -> bool:
    return any(words[i : i + len(key)] == key for i in range(max(0, at - shift), at + shift + 1))


def fit_idf(docs: DataFrame, index: LicenceIndex) -> LicenceIndex:
    """Document frequencies of the licence words over all documents; one small row per task reaches the driver."""
    vocabulary = sorted({w for t in index.templates for w in t.words})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, n, df = set(vocabulary), 0, Counter()
        for batch in batches:
            for text in as_bytes(batch.column(0)):
                n += 1
                df.update(known.intersection(words_of(text)))
        yield pa.RecordBatch.from_arrays([pa.array([n, *(df[w] for w in vocabulary)], pa.int64()), pa.array(range(len(vocabulary) + 1), pa.int32())], ["n", "slot"])

    rows = dict(docs.select("text").mapInArrow(run, "n bigint, slot int").groupBy("slot").sum("n").collect())
    return index.fit(rows.get(0, 0), {w: rows.get(i + 1, 0) for i, w in enumerate(vocabulary)})


def scan(docs: DataFrame, index: LicenceIndex, min_score: float = 0.6) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score of every document."""
    schema = "doc_id bigint, n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string, labels string, score double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1))):
                words = words_of(text)
                places, scores = scan_text(words, index)
                starts = [s for _, s in places]
                base = {index.templates[t].label for t, _ in places}
                good = {t: s for t, s in scores.items() if s >= min_score}
                labels = base | {index.templates[t].label for t in good}
                rows.append((doc, len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(base)), ",".join(sorted(labels)), float(max(good.values(), default=0.0))))
            kinds = [pa.int64()] * 5 + [pa.string()] * 2 + [pa.float64()]
            columns = [pa.array(x, k) for x, k in zip(zip(*rows), kinds)] if rows else [pa.array([], k) for k in kinds]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, schema)
