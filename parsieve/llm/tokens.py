"""Token counts of whole texts without token ids of documents.

The vocabulary's only normalisation is space -> U+2581 with one leading mark, and no
piece holds that mark behind another character, so no merge crosses the start of a run
of marks. A text therefore falls apart into pre-tokens (a run of marks and what follows
up to the next run) whose piece counts add up exactly. `TokenCounter` checks both
properties when it opens the vocabulary and refuses one that lacks them.

Each task keeps a dictionary pre-token -> pieces. A slice of rows becomes per-document
pre-token frequencies; pre-tokens that the dictionary lacks are encoded once; the
frequencies are joined to it and summed. A corpus-wide join of the same two relations
shuffles a row per (document, distinct pre-token), several times the input, for the
same sums (figures in the README), so the join stays inside the task.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from operator import mul

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from parsieve.llm.common import slices

MARK = "▁"
_RUNS = re.compile(r" +[^ ]*")


def pre_tokens(text: str) -> list[str]:
    """Pre-tokens without their first mark, further marks as spaces; joined by one space
    they give the text back."""
    if MARK in text:
        text = text.replace(MARK, " ")
    if not text:
        return []
    if "  " not in text and text[0] != " " and text[-1] != " ":
        return text.split(" ")
    return [run[1:] for run in _RUNS.findall(" " + text)]


class TokenCounter:
    """Counts pieces; `entries` and `longest` bound the dictionary, not the texts: a
    longer pre-token is encoded each time, a full dictionary starts anew."""

    def __init__(self, model_path: str, entries: int = 1_000_000, longest: int = 64):
        import sentencepiece

        self.sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
        self.entries, self.longest, self.known = entries, longest, {}
        pieces = [self.sp.id_to_piece(i) for i in range(self.sp.get_piece_size())]
        self.marked = np.array([p.startswith(MARK) for p in pieces])
        joined = any(MARK in p.lstrip(MARK) for p in pieces)
        probe = self.sp.encode(["ﬁ  x ", "ﬁ", "x"], out_type=str)
        if joined or probe[0] != [*probe[1], MARK, *probe[2], MARK]:
            raise ValueError("this vocabulary's pieces do not add up over pre-tokens")

    def _pieces(self, keys: list[str]) -> list[int]:
        """Pieces of each key. Keys without a space are encoded joined by spaces: every
        one then begins with the only piece of its own that starts with the mark."""
        out = dict.fromkeys(keys, 1)  # the empty pre-token is a lone mark: one piece
        plain = [k for k in keys if k and " " not in k]
        for i in range(0, len(plain), 2000):
            part = plain[i : i + 2000]
            ids = np.asarray(self.sp.encode(" ".join(part), num_threads=1), np.int64)
            first = np.flatnonzero(self.marked[ids])
            out.update(zip(part, np.diff(first, append=len(ids)).tolist(), strict=True))
        out.update((k, len(self.sp.encode(k, num_threads=1))) for k in keys if " " in k)
        return [out[k] for k in keys]

    def count(self, texts: list[str]) -> list[int]:
        frequencies = [Counter(pre_tokens(t)) for t in texts]
        if len(self.known) > self.entries:
            self.known.clear()
        known = self.known
        missing = list(set().union(*frequencies) - known.keys())
        short = [k for k in missing if len(k) <= self.longest]
        known.update(zip(short, self._pieces(short), strict=True))
        if len(short) == len(missing):
            return [sum(map(mul, map(known.__getitem__, f), f.values())) for f in frequencies]
        long = [k for k in missing if len(k) > self.longest]
        pieces = dict(zip(long, self._pieces(long), strict=True))
        return [sum((known[k] if k in known else pieces[k]) * n for k, n in f.items()) for f in frequencies]


def token_counts(docs: DataFrame, model_path: str, limit: int = 4096) -> DataFrame:
    """doc_id, n_bytes (UTF-8), n_tokens, over_limit (n_tokens > limit); a row per input row.

    Null and empty texts have no bytes and no tokens. Special strings inside a text are
    ordinary text. The vocabulary file must be at `model_path` on every executor.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = TokenCounter(model_path)
        for b in slices(batches):
            texts = [t or "" for t in b.column("text").to_pylist()]
            n_bytes = pa.compute.fill_null(pa.compute.binary_length(b.column("text")), 0).cast(pa.int64())
            tokens = counter.count(texts)
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), n_bytes, pa.array(tokens, pa.int64()), pa.array([n > limit for n in tokens], pa.bool_())],
                names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
