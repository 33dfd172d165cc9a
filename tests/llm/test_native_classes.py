"""Classes of near fingerprints come from DataFrame operations only."""

from pyspark.sql import DataFrame

from parsieve.llm import fingerprints


def test_no_python_on_the_executors(spark, monkeypatch):
    def refused(*_, **__):
        raise AssertionError("Python on the executors")

    prints = [0, 1, 3, 0b1111, 1 << 40, (1 << 40) | (1 << 63), 0xFF << 20, 0]
    rows = spark.createDataFrame([(i, f"{x:016x}") for i, x in enumerate(prints)], "doc_id long, fingerprint string")
    for kind in {DataFrame, type(rows)}:
        monkeypatch.setattr(kind, "mapInArrow", refused)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    kinds = sorted(set(prints))
    near = {x: {y for y in kinds if y != x and (x ^ y).bit_count() <= 1} for x in kinds}

    def reached(x):
        seen, rest = {x}, [x]
        while rest:
            rest = [z for y in rest for z in near[y] if z not in seen and not seen.add(z)]
        return f"{min(seen, key=signed):016x}"

    got = {r["doc_id"]: (r["near_links"], r["near_class"]) for r in fingerprints.with_links(spark, rows, radius=1).collect()}
    assert got == {i: (len(near[x]), reached(x)) for i, x in enumerate(prints)}
