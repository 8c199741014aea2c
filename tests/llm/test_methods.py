"""Operators against plain versions of their methods, on whole tables and at their edges."""

import hashlib
import heapq
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from tests.llm.test_dedup import brute_links, brute_removed, corpus

P = pytest.importorskip("public_tokenizers")
SMALL, TINY = "/root/testdata/sf0.01", "/root/testdata/sf0.001"


def documents(spark, sf_dir=SMALL):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


# --- whole tables against the libraries


def test_op1_equals_the_library_on_all_documents(spark):
    import sentencepiece

    from probseq.llm.queries import op1_sentencepiece
    from probseq.llm.sentencepieces import ChunkTable, _chunks

    sp = sentencepiece.SentencePieceProcessor(model_file=P.path("piece_bpe_32k.model"))
    got = {r["doc_id"]: tuple(r)[1:] for r in op1_sentencepiece(spark, SMALL).collect()}
    texts = {r["doc_id"]: r["text"] or "" for r in documents(spark).collect()}
    assert len(got) == len(texts)
    for k, t in texts.items():
        ids = [*sp.encode(t), sp.eos_id()]
        assert got[k] == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(sp.decode(ids).encode()).hexdigest())
    # one table: every distinct chunk goes through the model once
    table, chunks = ChunkTable(open(P.path("piece_bpe_32k.model"), "rb").read()), set()
    own = list(texts.values())
    for k in range(0, len(own), 50):
        table.encode(own[k : k + 50])
    for t in own:
        chunks |= set(_chunks.findall("▁" + t.replace(" ", "▁"))) if t else set()
    assert table.segmented == len(chunks)


def test_op5_equals_the_library_on_all_documents(spark):
    from tokenizers import Tokenizer

    from probseq.llm.queries import op5_packing

    t = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    pieces = {}
    rows = op5_packing(spark, SMALL).collect()
    for r in rows:
        pieces.setdefault(r["doc_id"], []).append(r)
    for r in documents(spark).collect():
        ids = np.array([*t.encode(r["text"] or "", add_special_tokens=False).ids, 1], "<u4")
        at = 0
        for p in sorted(pieces[r["doc_id"]], key=lambda p: p["start"]):
            assert p["start"] == at and p["doc_tokens"] == len(ids)
            assert p["ids_crc32"] == zlib.crc32(ids[at : at + p["length"]].tobytes())
            at += p["length"]
        assert at == len(ids)
    used = {}
    for r in rows:
        used[r["sequence_id"]] = used.get(r["sequence_id"], 0) + r["length"]
    assert max(used.values()) <= 2048 and len(used) <= 1.02 * sum(used.values()) / 2048 + 1


def test_op3_stored_bytes_by_another_reader(spark):
    """A reader of the test's own: element by element, fixed and EBML lacing."""
    from probseq.llm.matroska import indexed, store
    from probseq.llm.queries import op3_media

    def number(data, at, mark):
        width = 1
        while not data[at] & (0x80 >> (width - 1)):
            width += 1
        n = int.from_bytes(data[at : at + width], "big")
        return (n if mark else n - (1 << (7 * width))), at + width

    def payload(data, at=0, end=None):
        out, end = b"", len(data) if end is None else end
        while at < end:
            key, at = number(data, at, True)
            size, at = number(data, at, False)
            if key in (0x18538067, 0x1F43B675):
                out += payload(data, at, at + size)
            elif key == 0xA3:
                lacing, body = data[at + 3] >> 1 & 3, data[at + 4 : at + size]
                if not lacing:
                    out += body
                elif lacing == 2:
                    out += body[1:]
                else:
                    left, place = body[0], 1
                    for _ in range(left):
                        _, place = number(body, place, False)
                    out += body[place:]
            at += size
        return out

    media = {r["doc_id"]: bytes(r["media"]) for r in store(documents(spark)).collect()}
    got = {r["doc_id"]: r for r in op3_media(spark, SMALL).collect()}
    for r in documents(spark).collect():
        text = (r["text"] or "").encode()
        want = text + bytes(max(64, -(-len(text) // 64) * 64) - len(text))
        row = got[r["doc_id"]]
        assert payload(media[r["doc_id"]]) == want
        assert (row["n_bytes"], row["payload_bytes"], row["media_bytes"]) == (len(text), len(want), len(media[r["doc_id"]]))
        assert (row["payload_sha256"], row["tail_crc32"]) == (hashlib.sha256(want).hexdigest(), zlib.crc32(want[-64:]))
        assert row["media_sha256"] == hashlib.sha256(media[r["doc_id"]]).hexdigest()
    odd = spark.createDataFrame([(1, bytearray(b"nothing")), (2, None)], "doc_id long, media binary").withColumn("mine", F.lit(7))
    back = {r["doc_id"]: r for r in indexed(odd).collect()}
    assert back[1]["error"] and back[1]["packets"] == [] and back[2]["error"] is None and back[2]["mine"] == 7


# --- plain versions of methods


def test_op2_schedule_is_longest_processing_time(spark):
    from probseq.llm.queries import op2_sharding
    from probseq.llm.sharding import schedule

    def naive(sizes, shards):
        heap = [(0, s) for s in range(shards)]
        for n in sorted(sizes, reverse=True):
            load, s = heapq.heappop(heap)
            heapq.heappush(heap, (load + n, s))
        return sorted(load for load, _ in heap)

    r = random.Random(5)
    for _ in range(30):
        shards = r.randrange(1, 9)
        classes = [(str(n), float(n), r.randrange(1, 40)) for n in r.sample(range(1, 500), r.randrange(1, 20))]
        loads = [0.0] * shards
        for key, s, low, high in schedule(classes, shards):
            loads[s] += float(key) * (high - low)
        assert sorted(loads) == naive([n for _, n, c in classes for _ in range(c)], shards)
    rows = op2_sharding(spark, SMALL).collect()
    loads, groups, homes = [0] * 24, {}, {}
    for x in rows:
        loads[x["shard"]] += x["size"]
        homes.setdefault(x["text_crc32"], set()).add(x["shard"])
    for x in documents(spark).collect():
        body = (x["text"] or "").encode()
        groups[body] = groups.get(body, 0) + len(body) + 8
    best = naive(groups.values(), 24)
    assert len(rows) == documents(spark).count() and max(loads) <= best[-1] * 1.001 + 16
    assert sum(len(h) > 1 for h in homes.values()) == 0


def test_op8_gradient_and_stretches():
    from probseq.llm import quality as q

    r = np.random.default_rng(0)
    texts = [b"alpha beta, gamma! " * k for k in (3, 40, 11)] + [bytes(r.integers(32, 127, 700).astype(np.uint8)), b""]
    off = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    body = np.frombuffer(b"".join(texts), np.uint8)
    x, first = q.passages(body, off)
    y, weight = np.array([1, 0, 1, 0, 1.0], np.float32), np.array([1, 2, 1, 3, 1.0], np.float32)
    w = [p.astype(np.float64) for p in q._start(np.random.default_rng(1))]
    w[1] = r.uniform(0.05, 0.1, q.HIDDEN)  # a blank passage must not lie on the edge of the hidden layer

    def loss():
        p = q._forward(w, x, first)["p"]
        return float(-(weight * (y * np.log(p) + (1 - y) * np.log(1 - p))).sum() / weight.sum())

    grad = q._gradients(w, x, first, y, weight)
    for k, g in enumerate(grad):
        for at in zip(*(r.integers(0, n, 6) for n in w[k].shape), strict=True):
            kept, h = w[k][at], 1e-5
            w[k][at] = kept + h
            up = loss()
            w[k][at] = kept - h
            down = loss()
            w[k][at] = kept
            assert g[at] == pytest.approx((up - down) / (2 * h), rel=2e-3, abs=2e-6)
    # the mean of passages, weighted by attention, scores a bag; long texts in stretches score the same
    model = q.Model(np.zeros(q.WIDTH), np.ones(q.WIDTH), w)
    f = q._forward(w, x, first)
    for k, a in enumerate(first):
        b = first[k + 1] if k + 1 < len(first) else len(x)
        t, g = np.tanh(f["h"][a:b] @ w[2]), 1 / (1 + np.exp(-(f["h"][a:b] @ w[3])))
        e = np.exp((t * g) @ w[4])
        z = (e[:, None] / e.sum() * f["h"][a:b]).sum(axis=0)
        assert f["p"][k] == pytest.approx(1 / (1 + np.exp(-(z @ w[5] + w[6][0]))), rel=1e-9)
    whole = q.probabilities(model, body, off)
    assert whole == pytest.approx(f["p"])
    q.STRETCH, kept = 512, q.STRETCH
    assert q.probabilities(model, body, off) == pytest.approx(whole, rel=1e-6)
    q.STRETCH = kept
    again = q.Model.unpack(model.pack())
    assert all(np.array_equal(a, b) for a, b in zip(again.w, model.w, strict=True))


def test_op4_index_in_batches_equals_one_run(spark, tmp_path):
    from probseq.llm.suffixes import SuffixIndex, dedup

    docs = documents(spark, TINY).select("doc_id", "text").persist()
    want = {r["doc_id"]: (bytes(r["kept"]), r["n_removed"]) for r in dedup(docs).collect()}
    ids = sorted(want)
    cuts = [0, len(ids) // 2, 3 * len(ids) // 4, 7 * len(ids) // 8, len(ids)]
    index, got = SuffixIndex(spark, f"file://{tmp_path}", 4), {}
    for b in range(4):
        own = docs.where(F.col("doc_id").isin(ids[cuts[b] : cuts[b + 1]]))
        for _ in range(2 if b == 1 else 1):  # a batch that is added again changes nothing
            out = {r["doc_id"]: (bytes(r["kept"]), r["n_removed"]) for r in index.add(own, b).collect()}
        got |= out
        sizes = [n for _, n in index.levels(b)]
        assert all(x >= 2 * y for x, y in zip(sizes, sizes[1:], strict=False))
    assert got == want and sum(n for _, n in want.values()) > 0


def test_long_texts_in_stretches(spark):
    from probseq.llm import minhash, suffixes

    r = np.random.default_rng(4)
    words = [bytes(r.integers(97, 123, 5).astype(np.uint8)) for _ in range(400)]
    text = b" ".join(words[k] for k in r.integers(0, 400, 4000)) + b"\n" + b"x" * 3000
    body, off = np.frombuffer(text, np.uint8), np.array([0, len(text)])
    whole, contexts = minhash.word_hashes(body, off), suffixes.contexts(body, off)
    minhash.STRETCH, suffixes.STRETCH, kept = 1000, 1000, (minhash.STRETCH, suffixes.STRETCH)
    try:
        parts, split = minhash.word_hashes(body, off), suffixes.contexts(body, off)
    finally:
        minhash.STRETCH, suffixes.STRETCH = kept
    assert np.array_equal(parts[0], whole[0]) and parts[1].tolist() == whole[1].tolist()
    windows = lambda c: {(int(f) + k, int(a)) for f, w, a in zip(c[1], c[2], c[4], strict=True) for k in range(int(w) + 1)}
    assert windows(split) == windows(contexts) and len(windows(split)) == len(text) - 49
    # many megabytes in one value, and again inside another document
    big = (text * 260)[: 5 << 20]
    docs = spark.createDataFrame([(1, "q" * 60), (2, big.decode()), (3, "head " + big[1000:9000].decode())], "doc_id long, text string")
    rows = {x["doc_id"]: x for x in suffixes.dedup(docs).select("doc_id", "n_removed", "n_spans", "n_bytes").collect()}
    assert rows[2]["n_removed"] == 0 and rows[3]["n_removed"] >= 8000 and rows[3]["n_spans"] == 1
    got = {x["doc_id"]: x["n_shingles"] for x in minhash.link(docs, 2).collect()}
    found = big.split()
    assert got[2] == len(set(zip(found, found[1:], strict=False)))


# --- edges


EDGES = [(1, None), (2, ""), (3, "same text here " * 9), (3, "same text here " * 9), (4, "same text here " * 9), (None, "same text here " * 9), (5, " \t\n"), (6, "é" * 90)]


def edges(spark, extra):
    rows = spark.createDataFrame(EDGES, "doc_id long, text string")
    for name in extra:
        rows = rows.withColumn(name, F.lit("mine"))
    return rows


def operators():
    from probseq.llm import langid, matroska, minhash, packing, quality, sentencepieces, sharding, suffixes

    def languages(d):
        return langid.predict(d, langid.Trees.unpack(langid.grow({"en": [b"same text here"], "fr": [b"autre texte"]}).pack()))

    return {
        "op1": (lambda d: sentencepieces.encode(d, P.path("piece_bpe_32k.model")), 1),
        "op2": (lambda d: sharding.shard(d, 3), 1),
        "op3": (matroska.roundtrip, 1),
        "op4": (suffixes.dedup, 1),
        "op5": (lambda d: packing.pack_documents(d, P.path("word_bpe_49k.json"), 64, 1), 0),
        "op6": (lambda d: minhash.link(d, 2), 1),
        "op8": (lambda d: quality.score(d, None), 1),
        "op9": (languages, 1),
    }


@pytest.mark.parametrize("name", ["op1", "op2", "op3", "op4", "op5", "op6", "op8", "op9"])
def test_edges(spark, name):
    """Nulls, repeats, ties, clashing columns and empty tables; equal rows have equal results."""
    run, per_row = operators()[name]
    clash = ["ids", "_text", "_body", "_order", "score", "lang_pred", "shard", "slot", "group", "size", "kept", "node", "spots", "media", "rank", "n"]
    rows = [r.asDict(recursive=True) for r in run(edges(spark, clash)).collect()]
    plain = [r.asDict(recursive=True) for r in run(edges(spark, [])).collect()]
    key = lambda r: str(sorted((k, str(v)) for k, v in r.items()))
    assert sorted(map(key, rows)) == sorted(map(key, plain))
    if per_row:
        assert len(rows) == len(EDGES) and sorted(str(r["doc_id"]) for r in rows) == sorted(str(k) for k, _ in EDGES)
    if name not in ("op2", "op5"):  # these number rows
        twins = [r for r in rows if r["doc_id"] == 3]
        assert twins[0] == twins[1]
    assert run(edges(spark, clash).limit(0)).count() == 0


def test_vector_edges(spark):
    from probseq.llm.embeddings import link

    v = [1.0, 2.0, 3.0]
    rows = [(1, "a", v), (1, "a", v), (2, "a", v), (3, None, v), (None, "a", v), (5, "a", None), (6, "b", v), (7, "a", [2.0, 4.0, 6.0])]
    docs = spark.createDataFrame(rows, "vec_id long, label string, embedding array<double>").withColumn("rep", F.lit(1)).withColumn("v", F.lit(2))
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in link(docs).collect()}
    assert got == {1: (2, 1, True), 2: (2, 1, False), 3: (0, 3, True), None: (0, None, True), 5: (0, 5, True), 6: (0, 6, True), 7: (2, 1, False)}
    assert link(docs.limit(0)).count() == 0


def test_kept_columns_named_like_results(spark):
    from probseq.llm import langid, quality

    docs = edges(spark, ["score", "lang_pred", "excess"])
    keep = ["doc_id", "text", "score", "lang_pred", "excess"]
    trees = langid.grow({"en": [b"same text here"]})
    assert langid.predict(docs, trees, keep=keep).columns == keep and {r["score"] for r in langid.predict(docs, trees, keep=keep).collect()} == {"mine"}
    assert quality.score(docs, None, keep=["doc_id", "score"]).columns == ["doc_id", "score"]
    tied = langid.grow({"b": [b"xyz"], "a": [b"xyz"]})
    assert {r["lang_pred"] for r in langid.predict(edges(spark, []), tied).collect()} == {"a", "und"}


# --- the pipeline, stage by stage


def test_pipeline_stages_against_plain_versions(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    from probseq.llm import langid, quality
    from probseq.llm.common import settle

    stages = dict(pipeline.STAGES)
    texts = [*corpus(7, 50), "q" * 120, "zz " * 60]
    rows = [(k, t, "en", "s", len(t or "")) for k, t in enumerate(texts)]
    docs = settle(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").coalesce(2), "fixture")
    plain = lambda d: {r["doc_id"]: r["text"] for r in d.collect()}
    before = plain(docs)
    # language: code lengths of the same trees, one text at a time
    trees = langid.fit(docs, F.lit(True))
    kept = settle(stages["language"](spark, docs, SMALL), "fixture")
    want = {}
    for k, t in before.items():
        if t and any(c.isalpha() for c in t):
            b = t.encode()
            rate = langid.code_lengths(trees, np.frombuffer(b, np.uint8), np.array([0, len(b)]))[0] / len(b)
            if not (rate.min() / trees.rate[rate.argmin()] > pipeline.FOREIGN and len(b) >= pipeline.EVIDENCE):
                want[k] = t
    assert plain(kept) == want and len(want) < len(before)
    # quality: the whole of sf0.01, as labels teach there
    sf_docs = documents(spark)
    model = quality.fit(sf_docs, spark.read.parquet(f"{SMALL}/labels.parquet"), F.lit(True))
    good = set(plain(stages["quality"](spark, sf_docs, SMALL)))
    for k, t in plain(sf_docs).items():
        b = (t or "").encode()
        assert (k in good) == (quality.probabilities(model, np.frombuffer(b, np.uint8), np.array([0, len(b)]))[0] >= pipeline.QUALITY)
    # near-duplicates of five words
    ids = sorted(want)
    links = brute_links([want[k] for k in ids], ids, 5)
    apart = settle(stages["near_duplicates"](spark, kept, SMALL), "fixture")
    want = {k: want[k] for k, (_, least) in zip(ids, links, strict=True) if least == k}
    assert plain(apart) == want and len(want) < len(ids)
    # repeated passages
    ids = sorted(want)
    left = brute_removed([want[k] for k in ids], ids, 50)
    fresh = settle(stages["passages"](spark, apart, SMALL), "fixture")
    want = {k: t.decode("utf-8", "ignore") for k, t in zip(ids, left, strict=True)}
    assert plain(fresh) == want
    assert all(r["n_chars"] == len(r["text"]) for r in fresh.collect())
    # packing: as many tokens as the tokenizer makes
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    got = {r["doc_id"]: r["n"] for r in stages["packing"](spark, fresh, SMALL).groupBy("doc_id").agg(F.sum("length").alias("n")).collect()}
    assert got == {k: len(t.encode(x, add_special_tokens=False).ids) + 1 for k, x in want.items()}
