"""Language identification by prediction by partial matching over bytes.

Each language has a context tree of order ORDER: a node is a byte context, its counts
the bytes that followed it in that language's training texts. Escapes follow method C
(as many escape counts as distinct followers) with full exclusion: what a longer
context could have coded is taken out of the shorter ones. Statistics are frozen after
training, so the code length of a byte given its context is a number that can be worked
out once: `fit` turns the trees of all languages into one table

    state of the last ORDER bytes  ->  row of code lengths [byte class, language]

in which a state is the longest context that any language knows. A text's exact code
length under every language is then a gather and a sum. Bytes are grouped into classes
only where training never saw them; such a byte costs its class plus an equal share.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parsieve.llm.common import slices

ORDER = 3
UNKNOWN = "und"
MOST_BYTES = 1 << 30  # of the table of code lengths
STATES = 1 << 10  # whose code lengths are worked out at once; each takes some ten rows of doubles on the driver


class Trees(NamedTuple):
    """Frozen statistics of all languages.

    classes: byte -> class, class 0 for bytes that training never saw.
    state_of: packed classes of the last ORDER bytes -> state.
    bits: [state * n_classes + class, language], code length in bits.
    """

    languages: list[str]
    classes: np.ndarray
    n_classes: int
    state_of: np.ndarray
    bits: np.ndarray

    def lengths(self, texts: list[bytes]) -> np.ndarray:
        """Code length of each text under each language, in bits."""
        k, n_lang = self.n_classes, len(self.languages)
        sizes = np.array([len(t) for t in texts], np.int64)
        out = np.zeros((len(texts), n_lang))
        full = np.flatnonzero(sizes)
        if not len(full):
            return out
        # Every text is preceded by ORDER bytes of class 0, the start of all contexts.
        raw = np.frombuffer((b"\x00" * ORDER).join([b"", *(texts[i] for i in full)]), np.uint8)
        symbol = self.classes[raw]
        starts = ORDER + np.concatenate([[0], np.cumsum(sizes[full] + ORDER)[:-1]])
        lead = (starts[:, None] - np.arange(1, ORDER + 1)).ravel()
        symbol[lead] = 0
        context = np.zeros(len(symbol) - ORDER, np.int64)
        for j in range(ORDER):
            context = context * k + symbol[j : len(symbol) - ORDER + j]
        cost = self.bits[self.state_of[context].astype(np.int64) * k + symbol[ORDER:]]
        keep = np.ones(len(symbol), bool)
        keep[lead] = False
        cost = cost[keep[ORDER:]]
        bounds = np.concatenate([[0], np.cumsum(sizes[full])[:-1]])
        out[full] = np.add.reduceat(cost, bounds, axis=0, dtype=np.float64)
        return out

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float], list[float]]:
        """Language, posterior of that language under equal priors, bits per byte."""
        raw = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
        bits = self.lengths(raw)
        langs, scores, rates = [], [], []
        for t, r, b in zip(texts, raw, bits, strict=True):
            if not self.languages or not any(map(str.isalpha, t or "")):
                langs.append(UNKNOWN), scores.append(0.0), rates.append(0.0)
                continue
            best = int(b.argmin())
            langs.append(self.languages[best])
            scores.append(float(1 / np.exp2(np.maximum(b[best] - b, -1000)).sum()))
            rates.append(float(b[best] / len(r)))
        return langs, scores, rates


def _distribution(counts: np.ndarray, parent: list[np.ndarray]) -> np.ndarray:
    """Code lengths [state, symbol] from the counts of a state and of its ever shorter
    contexts (parent), by method C with exclusion; the last resort is uniform."""
    bits = np.zeros(counts.shape)
    left = np.ones(counts.shape, bool)  # symbols that no longer context could code
    spent = np.zeros(len(counts))  # bits of the escapes so far
    for level in [counts, *parent]:
        usable = np.where(left, level, 0)
        total, kinds = usable.sum(axis=1), (usable > 0).sum(axis=1)
        here = usable > 0
        with np.errstate(divide="ignore"):
            p = np.log2(total + kinds)[:, None] - np.log2(np.maximum(usable, 1e-300))
            escape = np.where(kinds > 0, np.log2(total + kinds) - np.log2(np.maximum(kinds, 1)), 0)
        bits = np.where(here, spent[:, None] + p, bits)
        spent = spent + escape
        left &= ~here
    rest = np.maximum(left.sum(axis=1), 1)
    return np.where(left, (spent + np.log2(rest))[:, None], bits)


def fit(counts: dict[str, tuple[np.ndarray, np.ndarray]]) -> Trees:
    """Trees from, per language, distinct (ORDER+1)-byte windows (uint64, oldest byte
    highest, value 256 for 'before the text') and how often each occurred."""
    languages = sorted(counts)
    if not languages:
        raise ValueError("no labelled text to learn from")
    windows = {lang: np.stack([(w >> np.uint64(16 * (ORDER - j))).astype(np.int64) & 0xFFFF for j in range(ORDER + 1)]) for lang, (w, _) in counts.items()}
    seen = np.unique(np.concatenate([w[-1] for w in windows.values()]))
    seen = seen[seen < 256]
    classes = np.zeros(257, np.int64)
    classes[seen] = np.arange(1, len(seen) + 1)
    k = len(seen) + 1
    unseen = 256 - len(seen)
    coded = {lang: classes[np.minimum(w, 256)] for lang, w in windows.items()}

    def pack(rows: np.ndarray) -> np.ndarray:
        key = np.zeros(rows.shape[1], np.int64)
        for r in rows:
            key = key * k + r
        return key

    # Known contexts of each order over all languages; state numbers run by order.
    known = [np.unique(np.concatenate([pack(c[ORDER - d : ORDER]) for c in coded.values()])) if d else np.zeros(1, np.int64) for d in range(ORDER + 1)]
    first = np.cumsum([0, *map(len, known)])
    state_of = np.zeros(k**ORDER, np.int32)
    every = np.arange(k**ORDER, dtype=np.int64)
    for d in range(1, ORDER + 1):
        slot = np.full(k**d, -1, np.int32)
        slot[known[d]] = first[d] + np.arange(len(known[d]))
        deeper = slot[every % k**d]
        state_of = np.where(deeper >= 0, deeper, state_of)
    if 4 * int(first[-1]) * k * len(languages) > MOST_BYTES:
        raise ValueError("the context trees are too large to send to every task")
    bits = np.empty((first[-1], k, len(languages)), np.float32)
    for column, lang in enumerate(languages):
        c, n = coded[lang], counts[lang][1].astype(float)
        table = []
        for d in range(ORDER + 1):
            t = np.zeros((len(known[d]), k))
            np.add.at(t, (np.searchsorted(known[d], pack(c[ORDER - d : ORDER])) if d else np.zeros(len(n), int), c[ORDER]), n)
            table.append(t)
        for d in range(ORDER + 1):
            for at in range(0, len(known[d]), STATES):
                part = known[d][at : at + STATES]
                shorter = [table[e][np.searchsorted(known[e], part % k**e) if e else np.zeros(len(part), int)] for e in range(d - 1, -1, -1)]
                bits[first[d] + at : first[d] + at + len(part), :, column] = _distribution(table[d][at : at + STATES], shorter)
    bits[:, 0] += math.log2(max(1, unseen))
    return Trees(languages, classes[:256].astype(np.uint8), k, state_of, bits.reshape(-1, len(languages)))


def windows_of(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (ORDER+1)-windows of the texts and their counts, as `fit` takes them."""
    pad = np.full(ORDER, 256, np.uint64)
    parts = [np.concatenate([pad, np.frombuffer(t, np.uint8).astype(np.uint64)]) for t in texts if t]
    keys = []
    for s in parts:
        w = np.zeros(len(s) - ORDER, np.uint64)
        for j in range(ORDER + 1):
            w = (w << np.uint64(16)) | s[j : len(s) - ORDER + j]
        keys.append(w)
    return np.unique(np.concatenate(keys), return_counts=True) if keys else (np.zeros(0, np.uint64), np.zeros(0, np.int64))


def in_training() -> F.Column:
    """Rows to learn from: crc32 of the decimal doc_id, modulo 3, is not 1."""
    return ~held_out()


def held_out() -> F.Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))


def train(docs: DataFrame, rows_per_language: int = 1500, languages: int = 2000) -> Trees:
    """Fits on a bounded sample of labelled rows: about `rows_per_language` whole texts of
    every label, chosen by a hash of doc_id against the label's row count, so the rows kept
    do not grow with the table. More than `languages` labels are an error, and so is a model
    of more than MOST_BYTES. Without a labelled text, as in an empty table, the trees know
    no language and every text is `und`."""
    rows = docs.select("doc_id", "text", "lang").where(in_training() & F.col("lang").isNotNull() & (F.length("text") > 0))
    sizes = rows.groupBy("lang").count().limit(languages + 1).collect()
    if len(sizes) > languages:
        raise ValueError(f"more than {languages} languages to learn")
    if not sizes:
        return Trees([], np.zeros(256, np.uint8), 1, np.zeros(1, np.int32), np.zeros((1, 0), np.float32))
    scale = 1 << 30
    share = F.create_map(*(F.lit(x) for r in sizes for x in (r["lang"], min(scale, math.ceil(scale * rows_per_language / r["count"])))))
    chosen = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(scale)) < F.coalesce(F.try_element_at(share, F.col("lang")), F.lit(0)))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            by: dict[str, list[bytes]] = {}
            for lang, text in zip(b.column("lang").to_pylist(), b.column("text").to_pylist(), strict=True):
                by.setdefault(lang, []).append(text.encode("utf-8", "surrogatepass"))
            for lang, texts in by.items():
                w, n = windows_of(texts)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(w), pa.string()), pa.array(w.view(np.int64)), pa.array(n, pa.int64())], names=["lang", "w", "n"])

    total = chosen.select("lang", "text").mapInArrow(count, "lang string, w long, n long").groupBy("lang", "w").agg(F.sum("n").alias("n")).toArrow()
    lang = pa.compute.dictionary_encode(total.column("lang")).combine_chunks()
    code, names = lang.indices.to_numpy(), lang.dictionary.to_pylist()
    w, n = total.column("w").to_numpy().view(np.uint64), total.column("n").to_numpy()
    return fit({name: (w[code == i], n[code == i]) for i, name in enumerate(names)})


def identify(docs: DataFrame, trees: Trees) -> DataFrame:
    """All columns of `docs` by which a caller joins are left out: returns doc_id,
    lang_pred, score (0..1), bits_per_byte, one row per input row.

    A null text and one without a letter are `und` with score 0. A tie between languages
    goes to the first by name. The text alone decides.
    """
    shared = docs.sparkSession.sparkContext.broadcast(trees)  # size fixed by the sample's bound

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            langs, scores, rates = shared.value.predict(b.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(rates, pa.float64())],
                names=["doc_id", "lang_pred", "score", "bits_per_byte"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double, bits_per_byte double")


def language_filter(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Pipeline stage: keeps the rows whose text has a language (`lang` is set to it). Where
    no row has a label nothing is learnt, every text is `und`, and no row stays."""
    trees = train(docs)
    shared = spark.sparkContext.broadcast(trees)
    columns = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            langs, _, _ = shared.value.predict(b.column("text").to_pylist())
            b = b.set_column(columns.index("lang"), "lang", pa.array(langs, pa.string()))
            yield b.filter(pa.array([x != UNKNOWN for x in langs], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
