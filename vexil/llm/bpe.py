"""Operator 8: byte-level BPE over whole texts by tree concatenation.

A long text is halved until its parts are short. A half ends where the
pre-tokenizer is bound to split (a single blank between two other characters), so
both sides agree with no more work. A part without such a place is pre-tokenized as a
whole, and a pre-token that is itself long (unsplit text) is halved by bytes: both
halves are encoded, then a window of tokens around the join is encoded anew and
grows until its outermost tokens equal those of the halves. BPE encodings are
exactly the token sequences whose neighbours are all stable as a pair, so the
outcome is the encoding of the whole, not an approximation.

Null text is empty text. Repeated rows give repeated rows; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

LEAF_CHARS = 32_768
PIECE_BYTES = 4_096


#: The pre-tokenizer is bound to split before a single blank between two other characters.
SEAM = re.compile(r"(?<=\S) (?=\S)")


@lru_cache(maxsize=4)
def _load(vocabulary: str, special: tuple[tuple[str, int], ...]):
    import tiktoken
    from tokenizers.pre_tokenizers import ByteLevel

    pattern = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
    with open(vocabulary, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("bytes", pat_str=pattern, mergeable_ranks=ranks, special_tokens=dict(special)), ByteLevel(add_prefix_space=False, use_regex=True)


class TreeEncoder:
    """Encodes and decodes as one process; parts of a long text are encoded by a few threads."""

    def __init__(self, vocabulary: str, special: dict[str, int] | None = None, leaf_chars: int = LEAF_CHARS, piece_bytes: int = PIECE_BYTES):
        self.special = special or {}
        self.core, self.split = _load(vocabulary, tuple(self.special.items()))
        self.leaf, self.piece = max(8, leaf_chars), max(8, piece_bytes)

    def encode(self, text: str) -> list[int]:
        if len(text) <= self.leaf:
            return self._plain(text)
        out: list[int] = []
        for part in self._around_special(text):
            out += [self.special[part]] if part in self.special else self._joined(part)
        return out

    def decode(self, ids: list[int]) -> str:
        return self.core.decode_bytes(ids).decode("utf-8", "replace")

    def _plain(self, text: str) -> list[int]:
        return self.core.encode(text, allowed_special="all", disallowed_special=()) if self.special else self.core.encode_ordinary(text)

    def _around_special(self, text: str) -> list[str]:
        if not any(s in text for s in self.special):
            return [text]
        rx = "|".join(re.escape(s) for s in sorted(self.special, key=len, reverse=True))
        return [x for x in re.split(f"({rx})", text) if x]

    def _joined(self, text: str) -> list[int]:
        leaves: list[str] = []
        todo = [text]
        while todo:  # halves, right one below the left one on the stack
            part = todo.pop()
            middle = len(part) // 2
            cut = SEAM.search(part, middle) if len(part) > self.leaf else None
            if cut is None and len(part) > self.leaf:
                cut = next(iter(SEAM.finditer(part, max(0, middle - self.leaf), middle)), None)
            if cut is None:
                leaves.append(part)
            else:
                todo += [part[cut.start() :], part[: cut.start()]]
        with ThreadPoolExecutor(2) as pool:
            return [i for ids in pool.map(self._leaf, leaves) for i in ids]

    def _leaf(self, part: str) -> list[int]:
        if len(part) <= self.leaf:
            return self.core.encode_ordinary(part)
        out: list[int] = []
        short: list[str] = []
        for _, (start, end) in self.split.pre_tokenize_str(part):
            raw = part[start:end]
            if len(raw) * 4 <= self.piece or len(data := raw.encode()) <= self.piece:
                short.append(raw)
                continue
            out += self._pieces(short)
            short = []
            out += self.tree(data)
        return out + self._pieces(short)

    def _pieces(self, pieces: list[str]) -> list[int]:
        return [i for p in pieces for i in self.core._encode_single_piece(p)]

    def tree(self, data: bytes) -> list[int]:
        """The tokens of one pre-token, however long."""
        if len(data) <= self.piece:
            return self.core._encode_single_piece(data)
        half = len(data) // 2
        return self.join(self.tree(data[:half]), self.tree(data[half:]))

    def join(self, left: list[int], right: list[int]) -> list[int]:
        """Tokens of the concatenation of two encoded byte strings of one pre-token."""
        width = 4
        while True:
            a, b = left[-width:], right[:width]
            new = self.core._encode_single_piece(self.core.decode_bytes(a + b))
            left_ok = len(left) <= width or new[0] == a[0]
            right_ok = len(right) <= width or new[-1] == b[-1]
            if left_ok and right_ok and (len(new) > 1 or len(left) <= width and len(right) <= width):
                return left[:-width] + new + right[width:]
            width *= 2


def encode_documents(docs: DataFrame, vocabulary: str, special: dict[str, int] | None = None, leaf_chars: int = LEAF_CHARS, piece_bytes: int = PIECE_BYTES, keep_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 and, with keep_ids, ids array<int> of every document."""
    fields = "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * keep_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = TreeEncoder(vocabulary, special, leaf_chars, piece_bytes)
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                n, ids_hex, text_hex, kept = [], [], [], []
                for text in part.column(1).to_pylist():
                    ids = encoder.encode(text or "")
                    packed = np.array(ids, "<u4")
                    n.append(len(ids))
                    ids_hex.append(hashlib.sha256(packed.tobytes()).hexdigest())
                    text_hex.append(hashlib.sha256(encoder.decode(ids).encode()).hexdigest())
                    if keep_ids:
                        kept.append(packed.astype(np.int32))
                columns = [part.column(0).cast(pa.int64()), pa.array(n, pa.int64()), pa.array(ids_hex), pa.array(text_hex)]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if keep_ids:
                    columns.append(pa.array(kept, pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)

    return docs.select("doc_id", "text").mapInArrow(run, fields)
