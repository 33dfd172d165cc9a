"""The full pairing of a bucket gives little more than links, however large the group."""

import random

from parsieve.llm import minhash


def test_far_copies_of_one_text_are_not_paired(spark, monkeypatch):
    rng = random.Random(11)
    base = [f"word{i}" for i in range(200)]
    texts = {0: base, 1: [*base[:199], "last"]}
    for d in range(2, 150):
        texts[d] = list(base)
        for at in rng.sample(range(200), 6):  # about 30 of 196 shingles: 0.74 to the base, 0.57 to others
            texts[d][at] = f"new{d}x{at}"
    texts[150] = [*texts[90][:50], "one", *texts[90][51:]]
    met, linked = [], minhash._Documents.linked

    def counted(self, cuts, pairs, *rest):
        met.append(pairs.count())
        return linked(self, cuts, pairs, *rest)

    monkeypatch.setattr(minhash._Documents, "linked", counted)
    docs = spark.createDataFrame([(d, " ".join(t)) for d, t in texts.items()], "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in minhash.near_duplicates(spark, docs).collect()}
    assert got == {d: d for d in texts} | {1: 0, 150: 90}
    assert len(met) > 1 and sum(met[1:]) < len(texts)
