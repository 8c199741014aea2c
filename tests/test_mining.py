"""Worked examples, golden values and properties of the miner."""

import random

import pytest

from probseq.config import IncrementParams, MiningParams
from probseq.functions import patterns as P
from probseq.operators import baselines, encode, evaluate, measures, postprocess, support
from probseq.operators.miner import mine_capped
from probseq.sources import toy
from probseq.sources.notation import occurrences, render


@pytest.fixture(scope="module")
def db(spark):
    occ = toy.toy_occurrences(spark).persist()
    return occ, toy.toy_weights(spark)


def good(run):
    return {r[0] for r in run.rows if r[-1]}


# Golden values: candidates of the tight and of the loose variant, and the frequent patterns.
WEIGHTED = {
    0.10: (15, 16, {"<(a)>", "<(a)(a)>", "<(a)(d)>", "<(a c)>", "<(b)>", "<(c)>", "<(c)(a)>", "<(d)>"}),
    0.15: (10, 12, {"<(a)>", "<(a)(a)>", "<(a c)>", "<(b)>", "<(c)>"}),
    0.20: (6, 12, {"<(a)>", "<(b)>", "<(c)>"}),
    0.30: (4, 5, {"<(a)>", "<(c)>"}),
}


@pytest.mark.parametrize("sup", sorted(WEIGHTED))
def test_toy_weighted(db, sup):
    tight = mine_capped(*db, MiningParams(sup))
    loose = mine_capped(*db, MiningParams(sup, support_cap="loose", weight_cap="global"))
    assert (tight.n_candidates, loose.n_candidates, good(tight)) == WEIGHTED[sup]
    assert good(loose) == good(tight)


def test_float_tie_counts(db):
    run = mine_capped(db[0], None, MiningParams(0.2))
    assert "<(a c)>" in good(run) and run.n_candidates == 5
    assert mine_capped(db[0], None, MiningParams(0.2, support_cap="loose")).n_candidates == 9


@pytest.mark.parametrize("kw", [{"engine": "relational"}, {"verify": "final_scan"}, {"prune": "exact"}, {"i_ext": "cooccurring"}])
def test_variants_agree(db, kw):
    assert good(mine_capped(*db, MiningParams(0.1, **kw))) == WEIGHTED[0.1][2]


@pytest.mark.parametrize("engine", ["arrow", "relational", "hof", "pairwise"])
def test_supports(spark, db, engine):
    pats = spark.createDataFrame([("<(a)(b)>",), ("<(a c)>",), ("<(z)>",)], "pattern string")
    got = {r["pattern"]: r for r in support.expected_support(db[0], pats, db[1], engine).collect()}
    r = got["<(a)(b)>"]
    assert r["support"] == 5 and r["es"] == pytest.approx(0.57) and r["seq_weight"] == pytest.approx(0.9) and r["wes"] == pytest.approx(0.513)
    assert got["<(z)>"]["es"] == 0


def test_caps_of_the_example(db):
    caps = {r["pattern"]: r for r in measures.pair_caps(db[0]).collect()}
    assert caps["<(a c)>"]["max_pr"] == pytest.approx(0.54) and caps["<(c)(a)>"]["max_pr"] == pytest.approx(0.42)
    assert caps["<(a)(a)>"]["es_cap"] == pytest.approx(2.25) and caps["<(a)(a)>"]["es_cap_loose"] == pytest.approx(3.78)
    assert caps["<(a)(d)>"]["es_cap"] == pytest.approx(0.72) and caps["<(a)(d)>"]["es_cap_loose"] == pytest.approx(1.26)
    s = measures.database_stats(*db).first()
    assert s["n_seq"] == 6 and s["wam"] == pytest.approx(0.877419, abs=1e-6)
    assert measures.database_stats(*db, "sequences").first()["wam"] == pytest.approx(0.888889, abs=1e-6)


def test_tree_pass(spark):
    occ = occurrences(spark.createDataFrame([(1, toy.TREE_SEQUENCE)], "seq_id long, sequence string"))
    pats = spark.createDataFrame([(p,) for p in toy.TREE_PATTERNS], "pattern string")
    got = {r["pattern"]: r["wes"] for r in support.expected_support(occ, pats, toy.toy_weights(spark)).collect()}
    want = {"<(a)>": 0.72, "<(b)>": 0.70, "<(a b)>": 0.486, "<(c)>": 0.27, "<(b)(c)>": 0.1995, "<(d)>": 0.81, "<(c d)>": 0, "<(c)(d)>": 0.243}
    assert got == pytest.approx(want)


def test_traps(spark):
    def mine(rows, weights, threshold):
        occ = occurrences(spark.createDataFrame(rows, "seq_id long, sequence string"))
        w = spark.createDataFrame(weights, "item string, weight double") if weights else None
        return {r[0]: r[-2] for r in mine_capped(occ, w, MiningParams(0.0), threshold).rows if r[-1]}

    assert mine([(1, "(a:0.9)(a:0.5, b:0.8)")], None, 0.3)["<(a b)>"] == pytest.approx(0.4)
    assert mine([(1, "(a:0.8)")], None, 0.5) == pytest.approx({"<(a)>": 0.8})
    assert mine([(1, "(b)(a)")], [("a", 0.1), ("b", 1.0)], 0.5) == pytest.approx({"<(b)>": 1.0, "<(b)(a)>": 0.55})


def test_precise_data_has_es_equal_to_support(db):
    run = baselines.mine_precise(db[0], 2)
    assert all(r["es"] == r["support"] for r in run.result.collect())
    assert {r["pattern"]: r["support"] for r in run.result.collect()}["<(a)(b)>"] == 5


def random_db(spark, seed):
    r = random.Random(seed)
    rows, w = [], [(x, round(r.uniform(0.1, 1), 3)) for x in "abcdef"]
    for s in range(8):
        events = [sorted(r.sample("abcdef", r.randint(1, 3))) for _ in range(r.randint(1, 5))]
        rows += [(s, k, x, round(r.uniform(0.05, 1), 3)) for k, e in enumerate(events) for x in e]
    return spark.createDataFrame(rows, "seq_id long, pos int, item string, p double").persist(), spark.createDataFrame(w, "item string, weight double"), round(r.uniform(0.4, 2), 3)


@pytest.mark.parametrize("seed", range(3))
def test_random_databases(spark, seed):
    occ, w, threshold = random_db(spark, seed)
    exact = {r["pattern"]: r["wes"] for r in baselines.mine_bruteforce(occ, w, threshold, 5).collect()}
    counts = []
    for s, g in (("tight", "local"), ("tight", "global"), ("loose", "global")):
        run = mine_capped(occ, w, MiningParams(0.0, support_cap=s, weight_cap=g, max_len=5), threshold)
        assert {r[0]: r[-2] for r in run.rows if r[-1]} == pytest.approx(exact)
        for r in run.rows:  # es <= tight <= loose, and the mean weight stays under the cap
            assert r[11] <= r[6] * (1 + 1e-9) and r[6] <= r[7] * (1 + 1e-9) and r[12] <= r[8] + 1e-9
        counts.append(run.n_candidates)
    assert counts == sorted(counts)
    assert {r["pattern"] for r in baselines.mine_generate_test(occ, w, threshold).collect()} == set(exact)


def test_probabilistic(spark, db):
    got = {r["pattern"]: r["probability"] for r in baselines.mine_probabilistic(db[0], 2, 0.3).collect()}
    best = [0.9, 0.6, 0.4, 0.3, 0.5, 0.1]
    assert got["<(a)>"] == pytest.approx(baselines.poisson_binomial_tail(best, 2))


def test_encoding(spark, db):
    sfx = {(r["seq_id"], r["pos"], r["item"]): r["p_sfx"] for r in encode.suffix_max(db[0]).collect()}
    assert [sfx[3, k, "a"] for k in (1, 2, 3)] == [0.4] * 3 and sfx[3, 2, "b"] == 0.3 and sfx[4, 1, "c"] == 0.4
    assert {r["seq_id"]: r["sequence"] for r in render(db[0]).collect()}[1] == "(a:0.9, c:0.6)(a:0.7)(b:0.3)(d:0.7)"
    bad = spark.createDataFrame([(1, 1, "a", 0.0), (1, 2, "a", 0.5), (1, 2, "a", 0.7), (1, 3, None, 0.5), (1, 4, "q", 1.5)], "seq_id long, pos int, item string, p double")
    assert sorted(r["reason"] for r in encode.faults(bad).collect()) == ["null", "probability", "probability", "repeated", "repeated"]
    assert [tuple(r) for r in encode.accepted(bad).collect()] == [(1, 2, "a", 0.7)]


def test_empty_input(spark):
    occ = spark.createDataFrame([], "seq_id long, pos int, item string, p double")
    assert mine_capped(occ, None, MiningParams(0.1)).result.count() == 0


def test_bad_options():
    for kw in ({"min_sup": 2}, {"min_sup": 0.1, "engine": "x"}, {"min_sup": 0.1, "wgt_fct": 0}, {"min_sup": 0.1, "max_len": 0}):
        with pytest.raises(ValueError):
            MiningParams(**kw)
    with pytest.raises(ValueError):
        IncrementParams(mu=0)


def test_post_processing(db):
    r = mine_capped(*db, MiningParams(0.1)).result.persist()
    assert [x["pattern"] for x in postprocess.top_k(r, 2).collect()] == ["<(a)>", "<(c)>"]
    assert {x["pattern"] for x in postprocess.maximal(r).collect()} == {"<(a)(a)>", "<(a)(d)>", "<(a c)>", "<(b)>", "<(c)(a)>"}
    rule = {(x["antecedent"], x["consequent"]): x["confidence"] for x in postprocess.rules(r, 0.0).collect()}
    assert rule["<(a)>", "<(d)>"] == pytest.approx(0.67 / 2.8)
    c = evaluate.completeness(r.limit(4), r).first()
    assert (c["found_n"], c["reference_n"], c["pct"]) == (4, 8, 50.0)


def test_pattern_functions(spark):
    steps = P.to_steps("<(a c)(b)>")
    assert steps == (("S", "a"), ("I", "c"), ("S", "b")) and P.to_text(steps) == "<(a c)(b)>"
    assert P.contains([["a", "c"], ["b"]], [["c"], ["b"]]) and not P.contains([["a", "c"]], [["a"], ["c"]])
    with pytest.raises(ValueError):
        P.extend(steps, "I", "a")
    row = spark.createDataFrame([("<(a c)(b)>", "<(c)(b)>")], "x string, y string").select(P.length("x").alias("n"), P.has(P.events("x"), P.events("y")).alias("has"), P.text(P.events("x")).alias("t")).first()
    assert (row["n"], row["has"], row["t"]) == (3, True, "<(a c)(b)>")
    from probseq.functions.sql import register_all

    occ = toy.toy_occurrences(spark)
    register_all(spark, occ)
    encode.packed_maps(occ).createOrReplaceTempView("packed")
    got = spark.sql("SELECT sum(best) AS es FROM (SELECT seq_id, max(pr) AS best FROM packed, LATERAL pattern_ends(events, '<(a)(b)>') GROUP BY seq_id)").first()
    assert got["es"] == pytest.approx(0.57)
    assert spark.sql("SELECT pattern_length('<(a c)(b)>') AS n").first()["n"] == 3


def test_plans(spark):
    from probseq.plans.inspect import has_cartesian, pushed_filters, read_columns
    from probseq.sources import tables

    df = tables.segment_brand_type(spark, "/root/testdata/sf0.001")
    assert not has_cartesian(df) and any("c_mktsegment" in f for f in pushed_filters(df))
    assert all("l_comment" not in c for c in read_columns(df))


def test_candidates_are_bound_by_parts_and_what_stands_beside_them(spark, monkeypatch):
    """a pattern is scanned only if each part, times the item that it lacks, reaches the threshold over the sequences."""
    import numpy as np

    from probseq.operators import miner
    from probseq.operators.support import expected_support

    rng = np.random.default_rng(3)
    rows = sorted({(s, int(e), f"i{int(i)}") for s in range(60) for e, i in zip(rng.integers(1, 9, 14), rng.integers(0, 8, 14), strict=True)})
    occ = spark.createDataFrame([(*r, float(p)) for r, p in zip(rows, rng.uniform(0.2, 0.9, len(rows)), strict=True)], "seq_id long, pos int, item string, p double").persist()
    w = spark.createDataFrame([(f"i{k}", 0.4 + 0.05 * k) for k in range(8)], "item string, weight double")
    run = mine_capped(occ, w, MiningParams(0.1, prune="exact"), 2.5)
    every = [f"<(i{a})(i{b}{c}i{d})>" for a in range(8) for b in range(8) for d in range(8) for c in (")(", " ") if c == ")(" or b < d]
    every += [f"<(i{a} i{b})(i{c})>" for a in range(8) for b in range(a + 1, 8) for c in range(8)] + [f"<(i{a} i{b} i{c})>" for a in range(8) for b in range(a + 1, 8) for c in range(b + 1, 8)]
    whole = {r["pattern"]: r["es"] for r in expected_support(occ, spark.createDataFrame([(x,) for x in every], "pattern string"), w).where("wes >= 2.5").collect()}
    found = {r["pattern"]: pytest.approx(r["es"]) for r in run.result.where("length = 3").collect()}
    assert found == whole and whole
    assert all(r[6] >= r[11] * (1 - 1e-9) for r in run.rows)  # no bound under the support
    monkeypatch.setattr(miner, "BESIDE", (0, 0))
    plain = mine_capped(occ, w, MiningParams(0.1, prune="exact"), 2.5)
    assert plain.n_frequent == run.n_frequent and plain.n_candidates > 1.1 * run.n_candidates
