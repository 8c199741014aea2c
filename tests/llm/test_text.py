"""Tokenizers, sharding, packing, media, archives: exact round trips and edge cases."""

import random
import zlib

import pytest
from pyspark.sql import functions as F

P = pytest.importorskip("public_tokenizers")

ODD = [None, "", " ", "▁ a", "a  b", "\ta\n\x00", "é ﬁ 中🎉", "don't STOP</s>", "<|endoftext|> x", "x" * 3000, "word " * 500, "same", "same"]


def docs(spark, texts=ODD, extra=True):
    rows = [(None if k == 3 else k, t, "en", "s", 0) for k, t in enumerate(texts)]
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    return d.withColumn("shard", F.lit("mine")).withColumn("_text", F.lit(1)) if extra else d


def test_sentencepiece_equals_the_library(spark):
    import sentencepiece

    from probseq.llm.sentencepieces import decode, encode

    model = P.path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=model)
    out = encode(docs(spark), model)
    got = {r["doc_id"]: (list(r["ids"]), r["decoded"]) for r in out.collect()}
    for k, t in enumerate(ODD):
        ids = sp.encode(t or "") + [2]
        assert got[None if k == 3 else k] == (ids, sp.decode(ids))
    assert {r["doc_id"]: r["decoded"] for r in decode(out.select("doc_id", "ids"), model).collect()} == {k: v[1] for k, v in got.items()}
    assert encode(docs(spark).limit(0), model).count() == 0


def test_chunk_table_stays_small():
    import sentencepiece

    from probseq.llm.sentencepieces import ChunkTable

    proto = open(P.path("piece_bpe_32k.model"), "rb").read()
    sp, table = sentencepiece.SentencePieceProcessor(model_proto=proto), ChunkTable(proto, chunk_limit=50)
    r = random.Random(3)
    for _ in range(5):
        texts = ["".join(r.choice("abc é\n") for _ in range(200)) for _ in range(20)]
        flat, n, dec = table.encode(texts)
        at = 0
        for t, k, d in zip(texts, n.tolist(), dec, strict=True):
            ids = sp.encode(t) + [2]
            assert flat[at : at + k].tolist() == ids and d == sp.decode(ids)
            at += k
        assert len(table) <= 50


def test_tokens_and_packing(spark):
    from tokenizers import Tokenizer

    from probseq.llm.packing import pack, sequences, windows

    spec = P.path("word_bpe_49k.json")
    t = Tokenizer.from_file(spec)
    pieces = windows(docs(spark), spec, 64).persist()
    packed = pack(pieces, 64).persist()
    rows = packed.collect()
    for k, text in enumerate(ODD):
        ids = t.encode(text or "", add_special_tokens=False).ids + [1]
        own = sorted((r for r in rows if r["doc_id"] == (None if k == 3 else k)), key=lambda r: r["start"])
        assert [x for r in own for x in r["ids"]] == ids
        assert all(r["ids_crc32"] == zlib.crc32(b"".join(i.to_bytes(4, "little") for i in r["ids"])) for r in own)
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert sorted(by) == list(range(len(by)))
    for spans in by.values():
        at = 0
        for o, n in sorted(spans):
            assert o == at
            at += n
        assert at <= 64
    full = {r["sequence_id"]: (len(r["ids"]), r["used"]) for r in sequences(packed, 64).collect()}
    assert all(n == 64 or n == u and u & (u - 1) == 0 for n, u in full.values())


@pytest.mark.parametrize("seed", range(20))
def test_best_fit_decreasing(seed):
    from probseq.llm.packing import best_fit_decreasing

    r = random.Random(seed)
    counts = {r.randrange(1, 65): r.randrange(1, 40) for _ in range(r.randrange(1, 25))}
    made = {first + k // per for _, _, per, first, many, _ in best_fit_decreasing(counts, 64) for k in range(per * many)}
    bins: list[int] = []
    for n in sorted((n for n, c in counts.items() for _ in range(c)), reverse=True):
        fit = [i for i, room in enumerate(bins) if room >= n]
        if fit:
            bins[min(fit, key=lambda i: bins[i])] -= n
        else:
            bins.append(64 - n)
    assert len(made) == len(bins)


def test_sharding(spark):
    from probseq.llm.sharding import earliest_places, shard

    r = random.Random(1)
    texts = ODD + ["y" * r.randrange(1, 400) for _ in range(400)] + ["hot"] * 150
    rows = shard(docs(spark, texts), 6).collect()
    assert len(rows) == len(texts)
    homes, loads, slots = {}, [0] * 6, {}
    for x in rows:
        homes.setdefault(x["group"], set()).add(x["shard"])
        loads[x["shard"]] += x["size"]
        slots.setdefault(x["shard"], []).append(x["slot"])
    assert all(len(h) == 1 for h in homes.values()) and max(loads) - min(loads) < 60
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert shard(docs(spark).limit(0), 6).count() == 0
    loads = [5.0, 0.0, 3.0]
    heap = list(loads)
    want = [0, 0, 0]
    for _ in range(40):
        k = min(range(3), key=lambda i: (heap[i], i))
        heap[k] += 2
        want[k] += 1
    assert earliest_places(loads, 2.0, 40) == want


@pytest.mark.parametrize("lacing", ["auto", "xiph", "ebml", "fixed"])
def test_matroska_round_trip(lacing):
    from probseq.llm.matroska import demux, mux, padded, payload_of

    r = random.Random(2)
    for n in (0, 1, 64, 511, 513, 4096, 4097, 70000):
        p = padded(bytes(r.randrange(256) for _ in range(n)))
        m = demux(data := mux(p, lacing))
        assert payload_of(data, m) == p and len(p) % 64 == 0
        assert [x.timestamp for x in m.packets] == [64 * k for k in range(len(m.packets))]
        assert {c for _, _, c in m.cues} == {x.cluster for x in m.packets}
    with pytest.raises(ValueError):
        demux(data[:-3])


def test_media_columns(spark):
    from probseq.llm.matroska import packets, roundtrip, store

    rows = roundtrip(docs(spark)).collect()
    assert len(rows) == len(ODD) and all(r["payload_bytes"] >= max(64, r["n_bytes"]) for r in rows)
    assert len({r["media_sha256"] for r in rows if r["doc_id"] in (11, 12)}) == 1
    table = packets(store(docs(spark))).collect()
    assert all(r["error"] is None and r["cued"] for r in table)
    bad = spark.createDataFrame([(1, bytearray(b"nothing"))], "doc_id long, media binary")
    assert packets(bad).first()["error"]


def test_warc(spark):
    from probseq.llm import warc

    long = "p" * 200
    rows = [(5, "u5", long), (3, "u3", long), (9, None, long), (1, "u1", "short"), (2, "u2", "short"), (7, "u7", None), (8, "u8", "é" * 80), (8, "u8", "é" * 80), (None, "n", long)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("archive", F.lit("x"))
    index = warc.write(pages)
    got = warc.read(index, with_payload=True).collect()
    assert len(got) == len(rows) and all(r["intact"] for r in got)
    kinds = {(r["page_id"], r["record_type"], r["refers_to"]) for r in got}
    assert {(3, "response", None), (5, "revisit", 3), (9, "revisit", 3), (None, "revisit", 3), (1, "response", None), (2, "response", None), (8, "response", None)} <= kinds
    assert all(r["payload_bytes"] == 200 for r in got if r["record_type"] == "revisit")
    assert warc.read(index, where=F.col("page_id") == 8).count() == 2
    assert warc.read(warc.write(pages.limit(0))).count() == 0
