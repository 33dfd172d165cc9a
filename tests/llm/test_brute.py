"""Operators against plain versions of themselves, on the whole smallest table and odd rows."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import pytest
import xxhash

from parsieve.llm import fingerprints, jpeg, langid, lines, minhash, mixing, packing, pii, secrets, tokens
from tests.llm.test_llm import SCHEMA, SF, linked, normal_lines, shingle_set


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def texts(docs):
    return {r["doc_id"]: r["text"] for r in docs.collect()}


@pytest.fixture(scope="module")
def odd(spark):
    """Null and repeated ids, null, empty and long texts, repeated rows, columns named as
    the operators' own."""
    long = " ".join(f"w{i % 977}" for i in range(9_000))
    rows = [(None, "alone here"), (None, "alone here"), (1, None), (2, ""), (3, "one two"), (3, "one two"), (4, long), (4, "another text"), (5, "  \n\n "), (6, "12 34")]
    extra = "part long, block string, rows int, dropped int, kept boolean, names string, bucket int, line_dedup long"
    return spark.createDataFrame([(d, t, None, "s", 3, 1, "b", 2, 3, True, "n", 4, 5) for d, t in rows], f"{SCHEMA}, {extra}")


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_fingerprints_are_plain_simhash(spark, docs, texts):
    def plain(text):
        votes, total = [0] * 64, 0
        for w in re.split(r"[\x20\x09-\x0D]+", text.lower()):
            if w:
                weight = fingerprints.WEIGHT if len(w) >= fingerprints.LONG else 1
                total += weight
                h = xxhash.xxh64_intdigest(w.encode(), seed=42)
                for i in range(64):
                    votes[i] += weight * (h >> i & 1)
        return f"{sum(1 << i for i in range(64) if 2 * votes[i] > total):016x}"

    got = {r["doc_id"]: r["fingerprint"] for r in fingerprints.document_fingerprints(spark, docs).collect()}
    assert got == {d: plain(t) for d, t in texts.items()}


def test_language_code_lengths_match_a_plain_coder():
    train = {"x": [b"abracadabra alakazam", b"bar aba"], "y": [b"zyzzyva zebra", b"azure zed"]}
    trees = langid.fit({k: langid.windows_of(v) for k, v in train.items()})
    alphabet = set(b"".join(t for v in train.values() for t in v))

    def plain(text, lang):
        known = defaultdict(Counter)
        for t in train[lang]:
            path = [None] * langid.ORDER + list(t)
            for i in range(langid.ORDER, len(path)):
                for d in range(langid.ORDER + 1):
                    known[tuple(path[i - d : i])][path[i]] += 1
        path, bits = [None] * langid.ORDER + [b if b in alphabet else None for b in text], 0.0
        for i in range(langid.ORDER, len(path)):
            out = set()
            for d in range(langid.ORDER, -1, -1):
                usable = {s: n for s, n in known[tuple(path[i - d : i])].items() if s not in out}
                if not usable:
                    continue
                total = math.log2(sum(usable.values()) + len(usable))
                if path[i] in usable:
                    bits += total - math.log2(usable[path[i]])
                    break
                bits += total - math.log2(len(usable))
                out |= set(usable)
            else:
                bits += math.log2(len(alphabet) + 1 - len(out)) + (math.log2(256 - len(alphabet)) if path[i] is None else 0)
        return bits

    probes = [b"abra", b"zzz zebra", b"q!", b"az bar \xc3\xa9"]
    for probe, got in zip(probes, trees.lengths(probes), strict=True):
        assert got.tolist() == pytest.approx([plain(probe, "x"), plain(probe, "y")], abs=1e-3)


def test_language_without_rows(none, odd):
    trees = langid.train(none)
    assert langid.identify(none, trees).count() == 0
    assert {r["lang_pred"] for r in langid.identify(odd, langid.train(odd)).collect()} == {"und"}


def test_media_payloads(docs, texts, odd, none):
    for r in jpeg.text_as_jpeg(docs).collect():
        raw = texts[r["doc_id"]].encode()
        padded = raw + b"\xff" * (max(1, -(-len(raw) // 576)) * 576 - len(raw))
        assert (r["n_bytes"], r["payload_bytes"]) == (len(raw), len(padded))
        assert r["payload_sha256"] == hashlib.sha256(padded).hexdigest() and r["tail_crc32"] == zlib.crc32(padded[-32:])
    rows = jpeg.text_as_jpeg(odd).collect()
    assert len(rows) == odd.count() and {r["payload_bytes"] for r in rows if not r["n_bytes"]} == {576}
    assert jpeg.text_as_jpeg(none).count() == 0


def test_mixing_odd_rows(spark, odd, none):
    out = mixing.mix_stage(spark, odd)
    assert out.columns == odd.columns
    assert sorted(map(repr, out.collect())) == sorted(map(repr, odd.collect()))
    assert mixing.mix_stage(spark, none).count() == 0


def test_cut_blocks_are_prefixes(spark):
    rows = [(i, "x" * (4 * (1 + i % 7)), None, "a" if i % 10 else "b", 1) for i in range(2000)]
    table = spark.createDataFrame(rows, SCHEMA)
    got = mixing.mixture(table, 1.5).collect()
    sizes = Counter()
    for i, t, _, s, _ in rows:
        sizes[s] += len(t) // 4
    chosen = mixing.plan(dict(sizes), 1.5)
    for s, passes in chosen.passes.items():
        own = [r for r in got if r["source"] == s]
        used, whole = sum(r["n_tokens"] for r in own), math.floor(passes)
        assert Counter(r["mix_pass"] for r in own)[0] == sum(x[3] == s for x in rows)
        assert passes * sizes[s] - 7 <= used <= passes * sizes[s] + 1e-6 and max(r["mix_pass"] for r in own) <= whole


def naive_pack(sizes, lengths, choose):
    bins = []
    for i, n in enumerate(sizes):
        fit = [b for b in bins if b[0] - b[1] >= n]
        if fit:
            b = min(fit, key=lambda b: b[0] - b[1])
        else:
            b = [choose(i, n), 0]
            bins.append(b)
        b[1] += n
    return sorted(next(c for c in lengths if c >= used) for _, used in bins)


def test_packing_matches_a_naive_one(docs, texts):
    lengths = packing.LENGTHS
    sizes = []
    for t in texts.values():
        n = len(t.split())
        sizes += [lengths[-1]] * (n // lengths[-1]) + ([n % lengths[-1]] if n % lengths[-1] else [])
    sizes.sort(reverse=True)

    def cheapest(i, n):
        rate = lambda c: packing.bin_cost(c) / (n + min(c - n, sum(s for s in sizes[i + 1 :] if s <= c - n)))
        return min((c for c in lengths if c >= n), key=rate)

    ways = [cheapest] + [lambda i, n, p=p: next(c for c in lengths if c >= n and (c >= p or c == lengths[-1])) for p in lengths]
    best = min(sum(map(packing.bin_cost, naive_pack(sizes, lengths, w))) for w in ways)
    got = {r["bin_id"]: r["bin_length"] for r in packing.packed(docs).collect()}
    assert sum(map(packing.bin_cost, got.values())) == best


def test_packing_odd_rows(odd):
    rows = packing.packed(odd).collect()
    total = sum(r["length"] for r in rows)
    assert total == sum(len((r["text"] or "").split()) for r in odd.collect())


def test_token_counts_are_the_library_s(docs, texts, odd, none):
    import sentencepiece

    from parsieve.llm.queries import vocabulary

    sp = sentencepiece.SentencePieceProcessor(model_file=vocabulary())
    for r in tokens.token_counts(docs, vocabulary()).collect():
        n = len(sp.encode(texts[r["doc_id"]]))
        assert (r["n_tokens"], r["n_bytes"], r["over_limit"]) == (n, len(texts[r["doc_id"]].encode()), n > 4096)
    assert sorted(r["n_tokens"] for r in tokens.token_counts(odd, vocabulary()).collect()) == sorted(len(sp.encode(r["text"] or "")) for r in odd.collect())
    assert tokens.token_counts(none, vocabulary()).count() == 0


def test_base_spans_match_the_patterns(docs, texts):
    def plain(t):
        out = []
        for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", t, re.I | re.A):
            if len(m[2]) >= 12:
                out.append((m.start(), 0, m.end()))
        out += [(m.start(), 1, m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 18]
        out += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 16]
        return sorted(out)

    for r in secrets.secret_spans(docs).collect():
        found = plain(texts[r["doc_id"]])
        listed = ",".join(f"{('assign', 'access', 'hex')[k]}:{a}:{b}" for a, k, b in found)
        assert r["base_sha256"] == hashlib.sha256(listed.encode()).hexdigest()
        assert [r["n_assign"], r["n_access"], r["n_hex"]] == [sum(k == i for _, k, _ in found) for i in range(3)]


def test_secrets_that_no_pattern_finds(spark):
    """Planted bare secrets are found by the ratio test, ordinary strings are left alone."""
    held = secrets.labelled_samples(400, "other-samples")
    secret = [s for s, y in held if y and not secrets.base_spans(s) and re.fullmatch(secrets.CANDIDATE, s)]
    plain = [s for s, y in held if not y and re.fullmatch(secrets.CANDIDATE, s)]
    rows = [(i, f"see {s} there", None, None, 1) for i, s in enumerate(secret + plain)]
    got = {r["doc_id"]: r["n_random"] for r in secrets.secret_spans(spark.createDataFrame(rows, SCHEMA)).collect()}
    hit = [got[i] > 0 for i in range(len(rows))]
    true, false = sum(hit[: len(secret)]), sum(hit[len(secret) :])
    assert len(secret) > 100 and len(plain) > 100
    assert true >= 0.97 * len(secret) and true >= 0.97 * (true + false)


def test_persons_keep_their_coreference(spark):
    t = ["Mr John Smith came. Mr Smith left; Dr no.", "Ms Lee-Ann Cho met Mr Smith", "10.0.0.300 is none, 10.0.0.30 is one"]
    got = [r["text"] for r in pii.pseudonymised(spark, spark.createDataFrame(list(enumerate(t)), "doc_id long, text string")).orderBy("doc_id").collect()]
    first = re.fullmatch(r"Mr (\S+) (\S+) came\. Mr (\S+) left; Dr no\.", got[0])
    assert first and first[2] == first[3] != "Smith" and first[1] != "John"
    second = re.fullmatch(r"Ms (\S+) (\S+) met Mr (\S+)", got[1])
    assert second and second[3] == first[2] and "Cho" not in got[1] and "Lee" not in got[1]
    assert got[2].startswith("10.0.0.300 is none, ") and "10.0.0.30 is" not in got[2]


def test_pii_odd_rows(spark, odd, none):
    rows = pii.pseudonymised(spark, odd.union(odd)).collect()
    assert Counter((r["doc_id"], r["text"]) for r in rows) == Counter((r["doc_id"], r["text"]) for r in odd.union(odd).collect())
    same = spark.createDataFrame([(None, "mail a.b@c.org now"), (None, "mail a.b@c.org now"), (7, "a.b@c.org")], "doc_id long, text string")
    out = [r["text"] for r in pii.pseudonymised(spark, same).collect()]
    assert len(out) == 3 and len({t.replace("mail ", "").replace(" now", "") for t in out}) == 1 and "a.b@" not in "".join(out)
    assert pii.pseudonymised(spark, none).count() == 0


def test_line_stage_keeps_clashing_columns(spark, odd):
    out = lines.line_dedup(spark, odd)
    assert out.columns == odd.columns and {r["dropped"] for r in out.collect()} == {3}


def test_ruled_lines_are_linked(spark):
    """Lines of which few shingles differ, and one edit in long lines."""
    words = " ".join(f"word{i * 37 % 101}" for i in range(60))
    rows = [(1, "=-" * 40), (2, "=-" * 38), (3, words), (4, words.replace("word74 ", "", 1)), (5, "short"), (6, "-" * 70), (7, "-" * 30)]
    gone = {(r["doc_id"], r["pos"]) for r in lines.repeated_lines(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert gone == {(2, 0), (4, 0), (7, 0)}


def test_pipeline_matches_brute_force(spark, docs, tmp_path):
    import corpus_pipeline

    some = docs.where("n_chars < 2500").limit(90)
    texts = [r.asDict() for r in some.collect()]
    texts += [dict(texts[i], doc_id=90_000 + i) for i in range(3)] + [dict(texts[0], doc_id=91_000, text="12 -- 34"), dict(texts[0], doc_id=91_001, text=None)]
    spark.createDataFrame(texts, docs.schema).write.parquet(str(tmp_path / "documents.parquet"))
    now = spark.read.parquet(str(tmp_path / "documents.parquet"))
    seen = []
    for i, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, now, str(tmp_path))
        out.write.parquet(str(tmp_path / f"stage{i}"))
        now = spark.read.parquet(str(tmp_path / f"stage{i}"))
        seen.append([r.asDict() for r in now.collect()])
    want = [r for r in texts if any(map(str.isalpha, r["text"] or ""))]
    assert sorted(r["doc_id"] for r in seen[0]) == sorted(r["doc_id"] for r in want)
    sets = {(r["doc_id"], i): {u[2 * k : 2 * (k + lines.Q)] for u in [x.encode("utf-16-be")] for k in range(max(0, len(u) // 2 - lines.Q) + 1)} for r in want for i, x in normal_lines(r["text"])}
    comp = linked(sets, lines.PERCENT)
    left = {r["doc_id"]: "\n".join(x for i, x in enumerate(r["text"].split("\n")) if comp.get((r["doc_id"], i), (r["doc_id"], i)) == (r["doc_id"], i)) for r in want}
    left = {d: t for d, t in left.items() if re.search(r"\S", t)}
    assert {r["doc_id"]: r["text"] for r in seen[1]} == left
    near = linked({d: shingle_set(t) for d, t in left.items()}, minhash.STAGE_PERCENT)
    kept = {d for d in left if near[d] == d}
    assert {r["doc_id"] for r in seen[2]} == kept and len(seen[2]) == len(kept)
    copies = Counter(r["doc_id"] for r in seen[3])
    assert set(copies) == kept and max(copies.values()) <= 2
    words = Counter()
    for r in seen[4]:
        words[r["doc_id"]] += r["length"]
    assert words == {d: n * len(left[d].split()) for d, n in copies.items()}


def test_pipeline_of_an_empty_table(spark, none, tmp_path):
    import corpus_pipeline

    none.write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
