"""op3 finds the near fingerprints of all documents."""

from parsieve.llm import queries

SF = "/root/testdata/sf0.001"


def test_links_of_documents_match_brute_force(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    long = docs.orderBy("doc_id").first()["text"]
    more = [(90_000 + i, long + " x" * i, "en", "a", 1) for i in range(6)] + [(None, long, "en", "a", 1)]
    both = docs.union(spark.createDataFrame(more, docs.schema))
    both.write.parquet(str(tmp_path / "documents.parquet"))
    rows = queries.op3_simhash(spark, str(tmp_path)).collect()
    assert len(rows) == both.count()
    fps = {int(r["fingerprint"], 16) for r in rows}
    signed = lambda f: f - (1 << 64) if f >> 63 else f
    near = {f: {g for g in fps if g != f and (f ^ g).bit_count() <= 3} for f in fps}
    assert any(near.values())
    least = {}
    for f in sorted(fps, key=signed):
        todo = [f]
        while todo:
            g = todo.pop()
            if g not in least:
                least[g] = f
                todo += near[g]
    for r in rows:
        f = int(r["fingerprint"], 16)
        assert (r["near_links"], r["near_class"]) == (len(near[f]), f"{least[f]:016x}")
