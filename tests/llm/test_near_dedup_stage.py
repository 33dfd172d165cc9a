"""The near-dedup stage of the pipeline links at 0.8, not at the threshold of op1."""

from parsieve.llm import minhash


def test_stage_drops_a_pair_at_0_82(spark):
    words = [f"word{i}" for i in range(104)]
    near = [*words[:50], "other", *words[51:]]  # 5 of 100 shingles changed on each side: 95 / 105
    far = [*words[:50], "other", *words[51:90], "more", *words[91:]]  # 90 / 110 = 0.818
    lone = [*words[:20], "a", *words[21:50], "b", *words[51:90], "c", *words[91:]]  # 85 / 115 = 0.739
    texts = {1: words, 2: far, 3: [f"x{w}" for w in words], 4: [f"x{w}" for w in near], 5: [f"y{w}" for w in words], 6: [f"y{w}" for w in lone]}
    docs = spark.createDataFrame([(d, " ".join(t)) for d, t in texts.items()], "doc_id long, text string")
    assert {r["doc_id"] for r in minhash.keep_one(spark, docs).collect()} == {1, 3, 5, 6}
    op1 = {r["doc_id"]: r["kept"] for r in minhash.near_duplicates(spark, docs).collect()}
    assert op1 == {1: True, 2: True, 3: True, 4: False, 5: True, 6: True}
