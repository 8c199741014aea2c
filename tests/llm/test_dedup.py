"""Near-duplicates, repeated passages, classifiers and vectors against brute force; edge cases."""

import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def corpus(seed=0, n=60):
    r = random.Random(seed)
    words = ["w%d" % k for k in range(300)]
    base = [" ".join(r.choice(words) for _ in range(r.randrange(20, 120))) for _ in range(8)]
    out = [None, "", " \n", "one", "one", "One", "two words", "a" * 400, "ab" * 200]
    for _ in range(n):
        t = r.choice(base).split()
        for _ in range(r.randrange(0, 12)):
            t[r.randrange(len(t))] = r.choice(words)
        if r.random() < 0.3:
            t += base[0].split()[:15]
        out.append(" ".join(t))
    return out


def frame(spark, texts):
    rows = [(None if k == 4 else k, t, "en", "s", 0) for k, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA).withColumn("node", F.lit("x")).withColumn("kept", F.lit(0))


def brute_links(texts, ids, words):
    sets = []
    for t in texts:
        w = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (t or "").encode()))
        sets.append({tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else ({tuple(w)} if w else set()))
    root = list(range(len(texts)))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                root[find(i)] = find(j)
    least = {}
    for k in range(len(texts)):
        least[find(k)] = min(least.get(find(k), 1 << 70), 1 << 69 if ids[k] is None else ids[k])
    return [(len(sets[k]), None if least[find(k)] == 1 << 69 else least[find(k)]) for k in range(len(texts))]


@pytest.mark.parametrize("words", [2, 5])
def test_minhash(spark, words):
    from probseq.llm.minhash import link

    texts = corpus()
    ids = [None if k == 4 else k for k in range(len(texts))]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in link(frame(spark, texts), words).collect()}
    want = dict(zip(ids, brute_links(texts, ids, words), strict=True))
    assert got == want
    assert link(frame(spark, texts).limit(0), words).count() == 0


def test_prefix_pairs_lose_none(spark):
    from probseq.llm.minhash import prefix_pairs, shingles

    texts = [t.encode() for t in corpus(3, 40) if t and len(t.split()) > 5]
    sets, sizes = shingles(np.frombuffer(b"".join(texts), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in texts])]), 2)
    stop = np.cumsum(sizes)
    parts = [sets[b - n : b] for b, n in zip(stop, sizes, strict=True)]
    rows = spark.createDataFrame([(k, k, bytearray(p.tobytes())) for k, p in enumerate(parts)], "node long, root long, items binary")
    found = {(r["a"], r["b"]) for r in prefix_pairs(rows, 80, 100).collect()}
    for i in range(len(parts)):
        for j in range(i + 1, len(parts)):
            both = len(np.intersect1d(parts[i], parts[j]))
            if 100 * both >= 80 * (len(parts[i]) + len(parts[j]) - both):
                assert (i, j) in found


def test_min_max_signature_is_unbiased():
    from probseq.llm.minhash import band_keys, least_agreement

    r = np.random.default_rng(1)
    hit, n = 0, 200
    for k in range(n):
        u = r.integers(0, 1 << 63, 100, dtype=np.uint64)
        a, b = np.sort(u[:90]), np.sort(u[10:])  # similarity 0.8
        keys, bits = band_keys(np.concatenate([a, b]), np.array([90, 90]), 40, 1, seed=k)
        hit += int((keys[0] == keys[1]).sum())
        assert 40 - sum(int(x).bit_count() for x in bits[0] ^ bits[1]) >= least_agreement(80, 100, 40, 1)
    assert hit / (40 * n) == pytest.approx(0.8, abs=0.03)


def brute_removed(texts, ids, span):
    first, out = {}, [None] * len(texts)
    order = sorted(range(len(texts)), key=lambda k: 1 << 69 if ids[k] is None else ids[k])
    for k in order:
        b, key = (texts[k] or "").encode(), 1 << 69 if ids[k] is None else ids[k]
        gone = bytearray(len(b))
        for s in range(len(b) - span + 1):
            w = b[s : s + span]
            if first.setdefault(w, key) < key:
                gone[s : s + span] = b"\1" * span
        out[k] = bytes(x for x, g in zip(b, gone, strict=True) if not g)
    return out


def test_suffix_dedup(spark):
    from probseq.llm.suffixes import dedup

    texts = [*corpus(5), "é" * 60, "xé" + "é" * 60, "q" * 120, "z" * 49 + "q" * 49, "q" * 50]
    ids = [None if k == 4 else k for k in range(len(texts))]
    want = brute_removed(texts, ids, 50)
    rows = {r["doc_id"]: r for r in dedup(frame(spark, texts)).collect()}
    for i, t, left in zip(ids, texts, want, strict=True):
        r = rows[i]
        assert bytes(r["kept"]) == left and r["n_removed"] == len((t or "").encode()) - len(left) and r["n_spans"] == len(r["removed"])
    assert dedup(frame(spark, texts).limit(0)).count() == 0
    twice = frame(spark, ["m" * 100]).unionByName(frame(spark, ["m" * 100]))
    assert [r["n_removed"] for r in dedup(twice).collect()] == [0, 0]


def test_suffix_marks_travel_by_home(spark):
    """What `met` sends grows with its tasks, not with texts times deals; a home may span record batches."""
    from pyspark.sql import functions as F

    from probseq.llm import suffixes as S

    shared = "".join(chr(97 + (k * k * 7 + k * 13 + (k >> 5) * 11) % 26) for k in range(5000))
    base = S._base(frame(spark, [f"{k:09d}" + shared for k in range(20)]).repartition(20), ["doc_id"], "doc_id", "text")
    entries = S.anchored(base, 16, S.SPAN, S.GRAM).withColumn("old", F.lit(False))
    met = S.met(S.dealt_out(entries, 16))
    tasks = S.partitions(spark)
    assert 20 <= met.count() <= 2 * 20 * tasks
    rows = S.marked(base, entries, 16, S.SPAN).select("_order", "_text_hash").collect()
    assert len(rows) == len(set(rows)) == 19
    texts = [*corpus(6), "m" * 120, "m" * 120, None, ""]
    ids = [None if k in (1, 3, 8) else k for k in range(len(texts))]
    docs = spark.createDataFrame(list(zip(ids, texts, strict=True)), "doc_id long, text string")
    want = sorted(brute_removed(texts, ids, 50))
    for most in ("1", "10000"):
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", most)
        try:
            assert sorted(bytes(r["kept"]) for r in S.dedup(docs).collect()) == want
        finally:
            spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_suffix_family():
    from probseq.llm.suffixes import SuffixFamily

    r = np.random.default_rng(0)
    family, seen = SuffixFamily(4), {}
    for doc in range(40):
        body = r.integers(0, 3, 60).astype(np.uint8)
        starts = np.arange(57)
        got = family.add(body, starts, np.full(57, doc))
        want = [seen.get(bytes(body[s : s + 4]), doc) < doc for s in starts]
        for s in starts:
            seen.setdefault(bytes(body[s : s + 4]), doc)
        assert got.tolist() == want
    sizes = [len(k) for k, _ in family.levels]
    assert len(sizes) < 8 and all(a >= 2 * b for a, b in zip(sizes, sizes[1:], strict=False))


def test_vectors(spark):
    from probseq.llm.embeddings import link, quantise, tile_links, unit

    r = np.random.default_rng(0)
    base = r.standard_normal((6, 16))
    rows = [(k, [float(np.float32(v)) for v in base[k % 6] + r.standard_normal(16) * r.choice([0.02, 0.06, 0.2])], k % 2) for k in range(120)]
    rows += [(200, None, 0), (201, [0.0] * 16, 0), (202, [float("nan")] * 16, 0), (203, rows[0][1], None), (204, rows[0][1], 0), (205, rows[0][1], 0), (206, [1.0, 2.0], 0), (207, [], 0)]
    got = {x["vec_id"]: (x["n_links"], x["component_id"], x["kept"]) for x in link(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int"), block=16).collect()}
    ok = [(k, np.array(v), y) for k, v, y in rows if v and y is not None and np.isfinite(v).all() and any(v)]
    root = {k: k for k, _, _ in rows}

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    n = dict.fromkeys(root, 0)
    for i, (a, x, p) in enumerate(ok):
        for b, y, q in ok[:i]:
            if p == q and len(x) == len(y) and x @ y / np.linalg.norm(x) / np.linalg.norm(y) >= 0.98:
                n[a] += 1
                n[b] += 1
                u, v = sorted((find(a), find(b)))
                root[v] = u
    assert got == {k: (n[k], find(k), find(k) == k) for k in root}
    x, y = unit(r.standard_normal((50, 64))), unit(r.standard_normal((50, 64)))
    q, s, c, e = quantise(x)
    t, u, d, g = quantise(y)
    gap = np.abs(x @ y.T - (s[:, None] * q) @ (u[:, None] * t).T)
    assert (gap <= c[:, None] * g + e[:, None] * d + e[:, None] * g).all()
    assert len(tile_links(x, x, 0.98)) == 50


def test_language_id(spark):
    from probseq.llm import langid

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    held = langid.remainder("doc_id", 4) == 2
    trees = langid.fit(docs, ~held)
    out = langid.predict(docs, trees).join(docs.select("doc_id", "lang"), "doc_id").where(held)
    right = out.where("lang_pred = lang").count()
    assert right >= 0.97 * out.count()
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "123 !!"), (4, "the thing and the other"), (5, "the " * 20000)], "doc_id long, text string")
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in langid.predict(odd, trees).collect()}
    assert [got[k][0] for k in (1, 2, 3)] == ["und"] * 3 and got[4][0] == got[5][0] == "en" and 0 < got[4][1] <= 1
    assert langid.predict(odd, None).where("lang_pred = 'und'").count() == 5


def test_code_lengths_equal_a_plain_coder():
    """Counts in dictionaries, one byte after another, against the tables; in whole texts and in blocks."""
    from math import log2

    from probseq.llm import langid

    r = np.random.default_rng(3)
    samples = {name: [bytes(r.choice(letters, n)) for n in (40, 7, 0, 90)] for name, letters in (("x", [97, 98, 99]), ("y", [98, 100]), ("z", [97, 200]))}
    for order in (0, 2, 5):
        trees = langid.grow(samples, order)
        seen = {name: {} for name in samples}
        for name, texts in samples.items():
            for t in texts:
                led = b"\n" * order + t
                for i in range(order, len(led)):
                    for k in range(order + 1):
                        own = seen[name].setdefault(led[i - k : i], {})
                        own[led[i]] = own.get(led[i], 0) + 1

        def cost(name, text):
            led, bits = b"\n" * order + text, 0.0
            for i in range(order, len(led)):
                for k in range(order, -1, -1):
                    own = seen[name].get(led[i - k : i])
                    if own is None:
                        continue
                    n, q = sum(own.values()), len(own)
                    if led[i] in own:
                        bits += log2((n + q) / own[led[i]])
                        break
                    bits += log2((n + q) / q)
                else:
                    bits += 8
            return bits

        texts = [b"abcab", b"", b"dbdbq", bytes([200, 97] * 9), b"\n", bytes(r.integers(0, 256, 3000).astype(np.uint8))]
        off = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
        body = np.frombuffer(b"".join(texts), np.uint8)
        want = [[cost(name, t) for name in trees.languages] for t in texts]
        for block in (1 << 18, 64):
            langid.BLOCK = block
            assert langid.code_lengths(trees, body, off) == pytest.approx(np.array(want), rel=1e-5)
        langid.BLOCK = 1 << 18
        again = langid.Trees.unpack(trees.pack())
        assert again.languages == trees.languages and np.array_equal(langid.code_lengths(again, body, off), langid.code_lengths(trees, body, off))


def test_quality(spark):
    from probseq.llm import quality
    from probseq.llm.langid import remainder

    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    held = remainder("doc_id", 5) == 0
    model = quality.fit(docs, labels, ~held)
    out = quality.score(docs, model).join(labels, "doc_id").where(held)
    good = out.where("(score >= 0.3) = (quality = 1)").count()
    assert good >= 0.95 * out.count()
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "x" * 100000)], "doc_id long, text string")
    assert all(0 <= r["score"] <= 1 for r in quality.score(odd, model).collect())
    assert {r["score"] for r in quality.score(odd, None).collect()} == {0.5}
    assert quality.attention(model, b"word " * 200).sum() == pytest.approx(1)


def test_pipeline(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet").withColumn("score", F.lit("mine"))
    for name, stage in pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns, name
        kept = out.count()
        assert 0 < kept <= docs.count()
        docs = out
    assert pipeline.STAGES[-1][1](spark, docs, sf).count() >= kept
