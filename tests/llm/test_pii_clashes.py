"""Every entity gets a surrogate, however small its format."""

import re

import pytest

from parsieve.llm import pii


def _apart(spark, entities):
    table = spark.createDataFrame([(e,) for e in entities], "entity string")
    got = {r["entity"]: r["surrogate"] for r in pii.surrogates(spark, table, "k").collect()}
    assert set(got) == set(entities) and len(set(got.values())) == len(entities)
    assert not set(got.values()) & set(entities)
    return got


def test_addresses_with_nothing_to_replace(spark):
    texts = ["see _@-.- here", "or +@-.com and it@mail.example.org", "_@-.- again"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in pii.pseudonymised(spark, docs).collect()}
    assert re.fullmatch(r"see (_[a-p]+@-\.-) here", got[0])
    assert got[2] == got[0].split()[1] + " again" and re.match(r"or \+[a-p]+@-\.com and ", got[1])


@pytest.mark.parametrize("kind", ["price", "latin", "cyrillic"])
def test_formats_that_run_out(spark, monkeypatch, kind):
    monkeypatch.setattr(pii, "ATTEMPTS", 4)  # fewer rounds; no more of them would do
    if kind == "price":
        got = _apart(spark, [f"{i // 10}@{i % 10}.99" for i in range(60)])
        assert all(re.fullmatch(r"[0-9][a-p]*@[0-9]\.99", s) for s in got.values())
    elif kind == "latin":
        # No name list holds more than one: all but one surname are left over.
        monkeypatch.setattr(pii, "NAMES", {k: v[:1] for k, v in pii.NAMES.items()})
        got = _apart(spark, [f"Mr. N{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(60)])
        assert all(re.fullmatch(r"Mr\. Abel[a-z-]*(-Abel[a-z]*)*", s) for s in got.values())
    else:
        monkeypatch.setattr(pii, "NAMES", {k: v[:1] for k, v in pii.NAMES.items()})
        _apart(spark, [f"Госпожа Н{chr(1072 + i)}" for i in range(30)])
