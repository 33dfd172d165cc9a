"""The driver works out code lengths for a bounded number of contexts at a time, with the same result."""

import random

import numpy as np

from parsieve.llm import langid


def test_contexts_go_in_parts(monkeypatch):
    rng = random.Random(2)
    texts = {lang: ["".join(rng.choices(letters, k=400)).encode() for _ in range(30)] for lang, letters in (("a", "abcdefghijklmnop qrst"), ("b", "opqrstuvwxyz éüabc"))}
    counts = {lang: langid.windows_of(t) for lang, t in texts.items()}
    sizes, work = [], langid._distribution
    monkeypatch.setattr(langid, "_distribution", lambda c, parent: (sizes.append(len(c)), work(c, parent))[1])
    parts = langid.fit(counts)
    assert max(sizes) <= langid.STATES < sum(sizes)
    monkeypatch.setattr(langid, "STATES", 1 << 40)
    whole = langid.fit(counts)
    assert np.array_equal(parts.bits, whole.bits) and np.array_equal(parts.state_of, whole.state_of)
