"""Secret scans: three fixed patterns, and a test of random against ordinary strings.

`CharModel` is a character Markov chain with additive smoothing. Two of them, one
trained on random strings and one on ordinary identifiers, are compared by their
log-likelihood ratio per character on every candidate string of a text; strings above
the threshold become spans of kind `random`. Of a string below it the parts between
separators are candidates in turn, so a secret in a path or an assignment is found too. Base spans are never removed or changed.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterable, Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from parsieve.llm.common import slices

# The base patterns and their least lengths, in the order of the kinds.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")  # the same spans as every maximal run, then the short ones dropped
LEAST_VALUE, LEAST_ACCESS = 12, 18
KINDS = ("assign", "access", "hex", "random")

LEAST_RANDOM = 16
CANDIDATE = re.compile(rf"[A-Za-z0-9+/_=-]{{{LEAST_RANDOM},}}")
# Separators by which a candidate falls into parts, the last ones also found in base64.
PARTED = tuple(re.compile(p) for p in (r"[^=]+", r"[^=_-]+", r"[^=_/-]+"))
_DIGIT = re.compile(r"[0-9]")
_HINT = re.compile(r"pass|secret|token|api", re.IGNORECASE)

ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-"


class CharModel:
    """log P(next | current) over ALPHABET plus an edge and a catch-all state."""

    def __init__(self, samples: Iterable[str], smoothing: float = 0.5):
        n = len(ALPHABET) + 2
        counts = np.full((n, n), smoothing)
        for s in samples:
            path = self.path(s)
            np.add.at(counts, (path[:-1], path[1:]), 1)
        self.log = np.log(counts / counts.sum(axis=1, keepdims=True))

    _index = np.full(256, len(ALPHABET) + 1, np.int64)
    _index[np.frombuffer(ALPHABET.encode(), np.uint8)] = np.arange(1, len(ALPHABET) + 1)

    @classmethod
    def path(cls, s: str) -> np.ndarray:
        inner = cls._index[np.frombuffer(s.encode("latin-1", "replace"), np.uint8)]
        return np.concatenate([[0], inner, [0]])


class SecretModel(NamedTuple):
    ratio: np.ndarray
    threshold: float

    def score(self, s: str) -> float:
        """Log-likelihood ratio per character, random against ordinary."""
        path = CharModel.path(s)
        return float(self.ratio[path[:-1], path[1:]].sum() / max(1, len(s)))

    def found(self, s: str, level: int = 0) -> Iterator[tuple[int, int]]:
        """(start, end) of s if it is above the threshold, else of its parts that are."""
        if self.score(s) > self.threshold:
            yield 0, len(s)
        elif level < len(PARTED):
            for m in PARTED[level].finditer(s):
                if m.end() - m.start() >= LEAST_RANDOM:
                    for a, b in self.found(m[0], level + 1):
                        yield m.start() + a, m.start() + b

    def highest(self, s: str) -> float:
        """The largest score of s and of its parts, as `found` tries them."""
        parts = (m[0] for p in PARTED for m in p.finditer(s) if len(m[0]) >= LEAST_RANDOM)
        return max(map(self.score, {s, *parts}))


def train(samples: Iterable[tuple[str, bool]], quantile: float = 0.999) -> SecretModel:
    """From (string, is_secret). The threshold is the given quantile of the ordinary
    samples' highest scores, 0 at least, so that about 1 - quantile of them would be marked."""
    rows = list(samples)
    random, ordinary = [s for s, y in rows if y], [s for s, y in rows if not y]
    ratio = CharModel(random).log - CharModel(ordinary).log
    model = SecretModel(ratio, 0.0)
    scores = [model.highest(s) for s in ordinary]
    return SecretModel(ratio, max(0.0, float(np.quantile(scores, quantile))) if scores else 0.0)


# Parts that ordinary identifiers in code and paths are made of.
PARTS = (
    "get set user name file path list index count value data table column row key map item node tree graph edge "
    "load save read write open close start stop run test main config option default handler manager service client "
    "server request response header body query result error message event queue task worker thread process buffer "
    "stream input output parse format encode decode token session account order customer product price total number "
    "date time update create delete find search filter sort group join split merge copy move check valid active first "
    "last next previous current parent child size length width height color image font text string integer float "
    "vector matrix model train batch layer weight version release build package module import export local global"
).split()

# Parts of long words in other languages of prose, which hold no digit either.
SYLLABLES = (
    "schaft heit keit ung lich isch ver ge be ent zer auf aus ein über schiff fahrt gesell haus zeit arbeit recht "
    "geber schutz kranken sicher pflicht sch chen pf tz ische einheit wissen stadt bahn strasse fracht dampf ober "
    "tion ment eau aux ou elle ette ique ance ence ouille pre con trans inter anti dis able ness less ship ing ight "
    "thing ent ion ough stre sion cion dad mente ando iendo ción zione mento ario istica bili tate ely ment ation"
).replace("ü", "ue").replace("ó", "o").split()


def _plain(h: bytes) -> str:
    """An ordinary string without words of code: a ruled line or a long word."""
    if h[0] % 4 == 0:
        pair = ("-=_/+"[h[1] % 5] + "-=_/+"[h[2] % 5], ALPHABET[h[1] % len(ALPHABET)] * 2)[h[3] % 2]
        return pair * (8 + h[4] % 24)
    s = "".join(SYLLABLES[h[j] % len(SYLLABLES)] for j in range(1, 6 + h[6] % 4))
    return (s, s, s.title(), s.upper())[h[7] % 4]


def labelled_samples(n: int = 4000, seed: str = "secret-samples") -> list[tuple[str, bool]]:
    """n secrets (base64, base62, hexadecimal), n ordinary identifiers with numbers and n
    ruled lines and long words, drawn from a keyed hash so that every run trains the same models."""
    rows: list[tuple[str, bool]] = []
    for i in range(n):
        h = hashlib.sha512(f"{seed}/{i}".encode()).digest()
        width = 20 + h[0] % 21
        coded = base64.b64encode(h).decode()
        rows.append(((h.hex(), coded, re.sub("[+/=]", "", coded))[h[1] % 3][:width], True))
        words = [PARTS[int.from_bytes(h[2 * j : 2 * j + 2], "big") % len(PARTS)] for j in range(2, 4 + h[3] % 4)]
        number = str(h[40] % (10, 100, 3000)[h[41] % 3])
        style = h[42] % 4
        if style == 0:
            s = "_".join([*words, number])
        elif style == 1:
            s = words[0] + "".join(w.title() for w in words[1:]) + number
        elif style == 2:
            s = "/".join([*words, "v" + number])
        else:
            s = "-".join([*words, number]).upper() if h[43] % 2 else "-".join([*words, number])
        rows += [(s, False), (_plain(h[44:]), False)]
    return rows


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind index, end) of the fixed patterns, in code points."""
    out = []
    if _HINT.search(text):
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= LEAST_VALUE]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    if _DIGIT.search(text) or "a" in text or any(c in text for c in "bcdef"):
        out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


def random_spans(text: str, model: SecretModel) -> list[tuple[int, int, int]]:
    """Candidates, or parts of them, that the random model explains better by the threshold."""
    return [(m.start() + a, 3, m.start() + b) for m in CANDIDATE.finditer(text) for a, b in model.found(m[0])]


def _listed(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def secret_spans(docs: DataFrame, model: SecretModel | None = None) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, n_random, base_sha256, spans; a row per input row.

    Spans are kind:start:end by start, then by the order of KINDS, in code points. Null
    and empty texts have none. The model has a fixed size and travels with the task.
    """
    model = model or train(labelled_samples())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            rows = []
            for text in b.column("text").to_pylist():
                base = base_spans(text or "")
                more = random_spans(text or "", model)
                n = [sum(k == kind for _, k, _ in base) for kind in range(3)]
                digest = hashlib.sha256(_listed(base).encode()).hexdigest()
                rows.append((*n, len(more), digest, _listed(sorted(base + more))))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), *(pa.array(c, pa.int64()) for c in cols[:4]), *(pa.array(c, pa.string()) for c in cols[4:])],
                names=["doc_id", "n_assign", "n_access", "n_hex", "n_random", "base_sha256", "spans"],
            )

    schema = "doc_id long, n_assign long, n_access long, n_hex long, n_random long, base_sha256 string, spans string"
    return docs.select("doc_id", "text").mapInArrow(run, schema)
