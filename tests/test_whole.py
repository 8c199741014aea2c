"""Queries that take all of their input: rows against the oracle where a cut would show."""

import glob
import os
from collections import Counter

import pytest

from probseq.workloads import ORACLES, QUERIES

duckdb = pytest.importorskip("duckdb")


def oracle(name, sf_dir, columns, sql=None):
    con = duckdb.connect()
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM read_parquet('{f}')")
    return Counter(map(tuple, con.execute(f"SELECT {', '.join(columns)} FROM ({sql or ORACLES[name]})").fetchall()))


def check(spark, name, sf_dir):
    df = QUERIES[name](spark, sf_dir)
    rows = Counter(tuple(r) for r in df.collect())
    assert rows == oracle(name, sf_dir, df.columns)
    return rows


def test_late_rows_covers_all_events(spark):
    rows = check(spark, "late_rows", "/root/testdata/sf0.01")
    events = spark.read.parquet("/root/testdata/sf0.01/events.parquet").count()
    assert sum(rows.values()) == events - 1 and any(r[0] >= 2000 and r[1] for r in rows)  # the first to arrive has none before it


def test_dialogue_takes_whole_turns(spark):
    import re

    from probseq.sources import tables

    sf_dir = "/root/testdata/sf0.001"
    want = set()
    for r in tables.table(spark, sf_dir, "conversations").collect():
        want |= {(r["conv_id"], r["turn"], x) for x in ["@" + r["role"], *re.findall("[a-z]+", r["text"].lower())]}
    got = [tuple(r) for r in tables.dialogue(spark, sf_dir).collect()]
    assert len(got) == len(set(got)) and set(got) == want


def test_sentences_and_pages_are_whole(spark):
    import re

    from probseq.sources import tables

    sf_dir = "/root/testdata/sf0.01"
    docs = {r["doc_id"]: r["text"].lower() for r in tables.table(spark, sf_dir, "documents").where("lang = 'en'").collect()}
    want = Counter()
    for d, text in docs.items():
        want.update(((d << 31) + k, n) for k, s in enumerate(re.split("[.!?\n]", text)) if (n := len(re.findall("[a-z]+", s))))
    got = Counter((r["seq_id"], r["n"]) for r in tables.sentence_words(spark, sf_dir).groupBy("seq_id").agg({"pos": "max"}).toDF("seq_id", "n").collect())
    assert got == want and max(n for _, n in want) > 40
    pages = {r["page_id"]: len(re.findall("<([a-zA-Z][a-zA-Z0-9]*)", r["html"])) for r in tables.table(spark, sf_dir, "pages").collect()}
    tags = {r["seq_id"]: r["n"] for r in tables.page_tags(spark, sf_dir).groupBy("seq_id").count().toDF("seq_id", "n").collect()}
    assert tags == {k: n for k, n in pages.items() if n} and max(tags.values()) > 60


@pytest.mark.parametrize("name", ["mine_sentence_words", "mine_curated_words", "mine_page_tags"])
def test_miners_of_whole_texts(spark, name):
    check(spark, name, "/root/testdata/sf0.01")


@pytest.mark.parametrize("kw", [{}, {"engine": "relational"}, {"verify": "final_scan"}, {"prune": "exact"}])
def test_a_small_candidate_bound_loses_nothing(spark, kw):
    from probseq.config import MiningParams
    from probseq.operators.miner import mine_capped
    from probseq.sources import toy

    db = toy.toy_occurrences(spark).persist(), toy.toy_weights(spark)
    whole, parts = (mine_capped(*db, MiningParams(0.1, max_candidates=n, **kw)) for n in (1_000_000, 2))
    values = lambda run: {r[0]: (r[10], *(round(x, 9) for x in (r[6], r[7], r[8], r[11], r[13])), r[-1]) for r in run.rows}
    assert values(parts) == values(whole) and whole.n_frequent == 8 and max(c["candidates"] for c in whole.counters) > 2
    assert [(c["tested"], c["candidates"]) for c in parts.counters] == [(c["tested"], c["candidates"]) for c in whole.counters]


def test_supplier_brand_has_no_length_limit(spark):
    from pyspark.sql import functions as F

    from probseq.config import MiningParams
    from probseq.operators.miner import mine_capped
    from probseq.workloads import MINERS, item_weights, occurrences

    kw = next(m[-1] for m in MINERS if m[0] == "mine_supplier_brand")
    occ = occurrences(spark, "/root/testdata/sf0.01", "supplier_brand").persist()
    w = item_weights(spark, occ, "supplier_brand")
    heavy = [r["item"] for r in w.orderBy(F.desc("weight"), "item").limit(6).collect()]
    run = mine_capped(occ.where(F.col("item").isin(heavy)), w, MiningParams(0.0, **kw), 48.01)  # the query's threshold
    found = {r[0]: r[-2] for r in run.rows if r[-1]}
    assert found["<(Brand#15)(Brand#17)(Brand#15)>"] == pytest.approx(51.62, abs=0.01)
    assert [c["frequent"] for c in run.counters] == [6, 35, 31, 0, 0] and run.counters[-1]["candidates"] == 0


def test_lightest_items_find_what_brute_force_finds(spark):
    import random

    from probseq.config import MiningParams
    from probseq.operators.baselines import mine_bruteforce
    from probseq.operators.miner import mine_capped

    r = random.Random(5)
    rows = [(s, k, x, round(r.uniform(0.2, 1), 2)) for s in range(12) for k in range(5) for x in "abcde" if r.random() < 0.5]
    occ = spark.createDataFrame(rows, "seq_id long, pos int, item string, p double").persist()
    w = spark.createDataFrame([("a", 0.3), ("b", 0.9), ("c", 0.6), ("d", 0.9), ("e", 0.1)], "item string, weight double")
    want = {x["pattern"]: (x["support"], round(x["wes"], 9)) for x in mine_bruteforce(occ, w, 1.6, 4).collect()}
    run = mine_capped(occ, w, MiningParams(0.0, prune="exact"), 1.6)
    assert {x["pattern"]: (x["support"], round(x["wes"], 9)) for x in run.result.collect()} == want
    assert max(map(len, want)) == len("<(a)(a)(a)>") and any(" " in p for p in want)
    assert mine_capped(occ, w, MiningParams(0.0, prune="exact", max_len=1), 1.6).n_frequent == sum(len(p) == 5 for p in want)


@pytest.mark.parametrize("name", ["mine_supplier_brand", "mine_dialogue"])
def test_heavy_items_end_the_search(spark, name):
    """The weight of the heaviest item as bound made these go through millions of candidates."""
    from probseq.workloads import MINERS, mined

    _, work, sup, weighted, _, kw = next(m for m in MINERS if m[0] == name)
    run = mined(spark, "/root/testdata/sf0.01", work, sup, weighted, **kw)
    assert run.n_candidates < 12_000
    assert [c["frequent"] for c in run.counters] == {"mine_supplier_brand": [12, 134, 46, 0, 0], "mine_dialogue": [52, 328, 1, 0]}[name]


def test_grouped_support_takes_many_sequences_at_once(spark):
    from pyspark.sql import functions as F

    from probseq.functions.aggregates import expected_support_by

    rows = [(s, k, x, 0.5) for s in range(6) for k, x in enumerate("ab" if s % 3 else "ca")]
    occ = spark.createDataFrame(rows, "seq_id long, pos int, item string, p double")
    got = expected_support_by(occ, "<(a)(b)>", (F.col("seq_id") % 3).alias("part"))
    assert sorted(map(tuple, got.collect())) == [(0, 0, 0.0), (1, 2, 0.5), (2, 2, 0.5)]
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "InPandas" not in plan and "ArrowAggregatePython" not in plan  # no Python call per sequence


def test_tree_arrays_read_the_events(spark):
    rows = check(spark, "tree_fig1_arrays", "/root/testdata/sf0.01")
    assert len({r[0] for r in rows}) == spark.read.parquet("/root/testdata/sf0.01/events.parquet").select("user_id").distinct().count()
    assert len({r[1] for r in rows}) == 8
