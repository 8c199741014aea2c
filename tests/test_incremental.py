"""Tiers after each batch of the worked example, replays, streams and splits."""

import pytest
from pyspark.sql import functions as F

from probseq.config import IncrementParams, MiningParams
from probseq.operators.incremental import ThreeTierMaintainer, TwoTierMaintainer
from probseq.operators.splits import bounds, growing_bounds, split_increments
from probseq.sources import toy


def parts(spark):
    occ = toy.toy_occurrences(spark).persist()
    return [occ.where(F.col("seq_id").between(a, b)) for a, b in ((1, 3), (4, 5), (6, 6))]


def states(spark, kind, path, **kw):
    m = kind(MiningParams(0.2), IncrementParams(**({"mu": 0.7, "gamma": 0.8} | kw)), toy.toy_weights(spark), path)
    p = parts(spark)
    m.initialize(p[0])
    for b in (1, 2):
        m.apply(p[b], b)
    return m, [{r["pattern"]: (r["tier"], r["wes"], r["exact"]) for r in m.tiers(spark, b).collect()} for b in range(3)]


def tier(state, name):
    return {k for k, v in state.items() if v[0] == name}


def test_three_tiers(spark, tmp_path):
    m, (s0, s1, s2) = states(spark, ThreeTierMaintainer, str(tmp_path))
    assert tier(s0, "FREQ") == {"<(a)>", "<(a)(a)>", "<(a)(d)>", "<(a c)>", "<(b)>", "<(c)>", "<(c)(a)>", "<(d)>"}
    assert tier(s0, "SEMI") == {"<(a)(a)(d)>", "<(a)(b)>", "<(a c)(a)>", "<(c)(d)>", "<(g)>"}
    assert tier(s1, "FREQ") == {"<(a)>", "<(a)(a)>", "<(a c)>", "<(b)>", "<(c)>"} and tier(s1, "SEMI") == {"<(d)>"}
    assert s1["<(a)(c)>"][:2] == ("PROMISING", pytest.approx(0.238)) and not s1["<(a)(c)>"][2]
    assert tier(s2, "FREQ") == {"<(a)>", "<(b)>", "<(c)>"} and tier(s2, "SEMI") == {"<(a)(a)>", "<(a c)>"}
    assert s2["<(a)(b)>"][:2] == ("PROMISING", pytest.approx(0.513)) and s2["<(b)(b)>"][:2] == ("PROMISING", pytest.approx(0.12))
    log = m.log[1]
    assert (log["wam"], log["min_wes"], log["min_wes_buf"], log["local_wes"]) == pytest.approx((0.869231, 0.86923, 0.60846, 0.19471), abs=1e-5)
    before = {r["pattern"]: r["wes"] for r in m.tiers(spark, 2).collect()}
    m.apply(parts(spark)[2], 2)  # a replay changes nothing
    assert {r["pattern"]: r["wes"] for r in m.tiers(spark, 2).collect()} == before
    moved = {r["pattern"]: (r["before"], r["after"]) for r in m.transitions(spark, 2).collect()}
    assert moved["<(a)(a)>"] == ("FREQ", "SEMI") and moved["<(b)(b)>"] == (None, "PROMISING")


def test_two_tiers(spark, tmp_path):
    _, (_, s1, s2) = states(spark, TwoTierMaintainer, str(tmp_path))
    assert tier(s2, "FREQ") == {"<(a)>", "<(b)>", "<(c)>"} and tier(s2, "SEMI") == {"<(a)(a)>", "<(a c)>"}
    assert not tier(s1, "PROMISING") and not tier(s2, "PROMISING")


def test_shared_work_gives_the_same_states(spark, tmp_path, monkeypatch):
    """Maintainers that share what they have in common end as those that do not, and mine each increment once."""
    from probseq.operators import incremental

    mined, real = [], incremental.mine_capped
    monkeypatch.setattr(incremental, "mine_capped", lambda *a: mined.append(a[3]) or real(*a))
    runs = [(ThreeTierMaintainer, 0.5), (TwoTierMaintainer, 0.7), (ThreeTierMaintainer, 1.0)]

    def all_states(name, shared):
        out = []
        for k, (kind, mu) in enumerate(runs):
            m = kind(MiningParams(0.2), IncrementParams(mu, 0.8), toy.toy_weights(spark), f"{tmp_path}/{name}{k}", *shared)
            p = parts(spark)
            m.initialize(p[0])
            for b in (1, 2):
                m.apply(p[b], b)
            s = m.drop_oldest(spark, 0, 3)
            out.append([{r["pattern"]: (r["tier"], round(r["wes"], 9), r["since_batch"], r["exact"]) for r in x.collect()} for x in (m.tiers(spark, 1), m.tiers(spark, 2), s)])
        return out

    alone = all_states("alone", ())
    assert len(mined) == 7
    mined.clear()
    assert all_states("shared", (incremental.Shared(toy.toy_weights(spark), f"{tmp_path}/common"),)) == alone
    assert len(mined) == 3


def test_one_mining_serves_all_thresholds(spark, monkeypatch):
    from probseq.operators import incremental

    mined, real = [], incremental.mine_capped
    monkeypatch.setattr(incremental, "mine_capped", lambda *x: mined.append(1) or real(*x))
    occ, w = toy.toy_occurrences(spark).persist(), toy.toy_weights(spark)
    shared = incremental.Shared(w, "")
    for sup in (0.15, 0.2, 0.3):
        p = MiningParams(sup, prune="exact")
        got, want = shared.mine(occ, p, None, 0), real(occ, w, p)
        assert got.threshold == pytest.approx(want.threshold)
        assert {r["pattern"] for r in got.result.collect()} == {r["pattern"] for r in want.result.collect()}
    assert len(mined) == 1


def test_large_gamma_is_clamped(spark, tmp_path):
    m, _ = states(spark, ThreeTierMaintainer, str(tmp_path), gamma=50.0)
    assert m.log[1]["clamped"]


def test_sliding_database(spark, tmp_path):
    """Dropping the oldest batch: every pattern has exactly what the sequences that stay gave it since it is tracked."""
    from probseq.operators.support import expected_support

    m, (_, _, s2) = states(spark, ThreeTierMaintainer, str(tmp_path))
    p, w = parts(spark), toy.toy_weights(spark)
    since = {r["pattern"]: r["since_batch"] for r in m.tiers(spark, 2).collect()}
    pats = spark.createDataFrame([(k,) for k in s2], "pattern string")
    per = [{r["pattern"]: r["wes"] for r in expected_support(d, pats, w).collect()} for d in p]
    got = {r["pattern"]: (r["tier"], r["wes"]) for r in m.drop_oldest(spark, 0, 3).collect()}
    s = m.log[-1]
    want = {}
    for k in s2:
        wes = sum(per[b][k] for b in (1, 2) if b >= since[k])
        name = "FREQ" if wes >= s["min_wes"] else "SEMI" if wes >= s["min_wes_buf"] else "PROMISING" if wes >= s["local_wes"] else None
        if name and wes > 1e-12:
            want[k] = (name, pytest.approx(wes))
    assert got == want and {t for t, _ in got.values()} == {"FREQ", "SEMI", "PROMISING"}
    assert s["n_seq"] == 3 and got["<(a)(c)>"][1] == pytest.approx(s2["<(a)(c)>"][1])  # admitted after the batch that went
    # the next increment goes on from there
    again = {r["pattern"]: r["wes"] for r in m.apply(p[2].withColumn("seq_id", F.col("seq_id") + 100), 4).collect()}
    assert again["<(a)>"] == pytest.approx(got["<(a)>"][1] + per[2]["<(a)>"]) and m.log[-1]["n_seq"] == 4


def test_own_local_threshold_and_plain_weights(spark, tmp_path):
    p = parts(spark)
    seen = []
    for k, local in enumerate((0.3, lambda s: seen.append(s["delta_n"]) or 0.3)):
        m = ThreeTierMaintainer(MiningParams(0.2), IncrementParams(0.7, 0.8, local), None, f"{tmp_path}/{k}")
        m.initialize(p[0])
        m.apply(p[1], 1)
        assert m.log[-1]["local_wes"] == 0.3 and all(r["wes"] >= 0.3 - 1e-9 and r["seq_weight"] == 1.0 for r in m.tiers(spark, 1).collect())
    assert seen and seen[-1] == 2


def test_splits(spark):
    assert bounds(0.5, 5)[0] == 0.5 and bounds(0.5, 5)[-1] == 1.0 and growing_bounds(0.3)[-1] == 1.0
    occ = toy.toy_occurrences(spark)
    s = split_increments(occ, [0.5, 1.0])
    assert s.groupBy("seq_id").agg(F.countDistinct("batch_id").alias("n")).where("n > 1").count() == 0
    with pytest.raises(ValueError):
        split_increments(occ, [1.0], "x")


def test_stream_equals_batches(spark, tmp_path):
    from probseq.streaming.increments import growing_support, run_increments

    schema = "seq_id long, pos int, item string, p double"
    src = tmp_path / "in"
    for k, p in enumerate(parts(spark)):
        p.select("seq_id", F.col("pos").cast("int").alias("pos"), "item", "p").coalesce(1).write.parquet(str(src / f"b{k}"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(src))
    m = ThreeTierMaintainer(MiningParams(0.2), IncrementParams(0.7, 0.8), toy.toy_weights(spark), str(tmp_path / "state"))
    run_increments(stream, m, str(tmp_path / "ck")).awaitTermination(240)
    _, (_, _, s2) = states(spark, ThreeTierMaintainer, str(tmp_path / "batch"))
    assert {r["pattern"]: r["wes"] for r in m.tiers(spark, 2).collect()} == pytest.approx({k: v[1] for k, v in s2.items()})
    out = growing_support(stream, [[["a"], ["b"]]])
    q = out.writeStream.format("memory").queryName("changes").option("checkpointLocation", str(tmp_path / "ck2")).trigger(availableNow=True).start()
    q.awaitTermination(240)
    assert spark.sql("SELECT sum(change) AS es FROM changes").first()["es"] == pytest.approx(0.57)


def test_text_format(spark, tmp_path):
    from probseq.sources.text import SequenceTextSource, parse_lines, to_lines

    occ = toy.toy_occurrences(spark)
    lines = to_lines(occ)
    key = lambda d: sorted((r["seq_id"], r["pos"], r["item"], r["p"]) for r in d.collect())
    assert key(parse_lines(lines)) == key(occ)
    f = tmp_path / "s.txt"
    f.write_text("\n".join(r["value"] for r in lines.orderBy("seq_id").collect()) + "\n")
    spark.dataSource.register(SequenceTextSource)
    got = spark.read.format("sequence_text").option("path", str(f)).option("split_bytes", 40).load()
    assert got.count() == occ.count() and got.select("seq_id").distinct().count() == 6


def test_packed_increments_give_counts_and_supports_without_moving_rows(spark):
    """Rows that lie by sequence are packed where they are, once, and the packed rows tell what the dictionary does."""
    from probseq.operators.encode import dictionary, packed_once
    from probseq.operators.miner import mine_capped
    from probseq.operators.support import expected_support, packed_support

    occ, w = toy.toy_occurrences(spark).repartition(3, "seq_id").persist(), toy.toy_weights(spark)
    occ.count()
    packed = packed_once(occ)
    assert packed.rows.rdd.getNumPartitions() == 3 and packed.n_seq == 6
    want = {r["item"]: (r["occ"], r["seqs"], pytest.approx(r["mx"]), pytest.approx(r["sm"])) for r in dictionary(occ).collect()}
    assert {x[0]: x[1:] for x in packed.items} == want
    for threshold in (0.2, 0.9):
        p = MiningParams(0.2, prune="exact")
        got, other = mine_capped(occ, w, p, threshold, packed), mine_capped(occ, w, p, threshold)
        key = lambda run: {r["pattern"]: (r["support"], pytest.approx(r["wes"])) for r in run.result.collect()}
        assert {k: v for k, v in key(got).items()} == {r["pattern"]: (r["support"], r["wes"]) for r in other.result.collect()}
    some = ["<(a)(b)>", "<(a c)(a)>", "<(a b)>", "<(z)(a)>", "<(a)>"]
    es = {r["pattern"]: pytest.approx(r["es"]) for r in expected_support(occ, spark.createDataFrame([(x,) for x in some], "pattern string")).collect()}
    assert packed_support(packed, some) == es
    packed.close()


def test_children_found_together_are_those_found_one_by_one():
    import numpy as np

    from probseq.operators.kernel import Batch, Families, totals, walk
    from probseq.operators.support import tree_of

    rng = np.random.default_rng(7)
    for n_seq in (1, 20, 400):
        rows = [sorted({(int(e), int(i)) for e, i in zip(rng.integers(0, 6, 12), rng.integers(0, 5, 12), strict=True)}) for _ in range(n_seq)]
        flat = [x for r in rows for x in r]
        batch = Batch(np.array([len(r) for r in rows]), np.array([e for e, _ in flat]), np.array([i for _, i in flat]), rng.random(len(flat)))
        two = [(("S", a), (k, b)) for a in range(-1, 7) for b in range(-1, 7) for k in "SI"]
        tree, nodes = tree_of(two + [(*x, ("S", c)) for x in two[::3] for c in (0, 3, 6)], {x: x for x in range(-1, 7)})
        want, got = (np.zeros(len(nodes)), np.zeros(len(nodes), int)), (np.zeros(len(nodes)), np.zeros(len(nodes), int))

        def visit(k, state, want=want):
            want[0][k] += state.best.sum()
            want[1][k] += len(state.rows)

        walk(batch, tree, tree.children(), visit)
        totals(batch, tree, Families(tree), *got)
        assert np.allclose(want[0], got[0], rtol=1e-12) and (want[1] == got[1]).all()


def test_blocks_hold_the_sequences_of_every_part(spark):
    """Parts of packed blocks tell what each part's own dictionary does, and are mined as its rows are."""
    from probseq.operators.encode import dictionary, in_blocks, packed_parts
    from probseq.operators.miner import mine_capped

    occ, w = toy.toy_occurrences(spark).withColumn("batch_0", (F.col("seq_id") % 2).cast("int")), toy.toy_weights(spark)
    kept = in_blocks(occ.repartition(3, "seq_id"), ["batch_0"]).persist()
    for own, packed in [(occ, packed_parts(kept)[0]), *((occ.where(F.col("batch_0") == b), x) for b, x in packed_parts(kept, "batch_0", range(2)).items())]:
        want = {r["item"]: (r["occ"], r["seqs"], pytest.approx(r["mx"]), pytest.approx(r["sm"])) for r in dictionary(own).collect()}
        assert {x[0]: x[1:] for x in packed.items if x[1]} == want and packed.n_seq == own.select("seq_id").distinct().count()
        p = MiningParams(0.2, prune="exact")
        got, other = mine_capped(own, w, p, 0.2, packed), mine_capped(own, w, p, 0.2)
        assert {r["pattern"]: (r["support"], pytest.approx(r["wes"])) for r in got.result.collect()} == {r["pattern"]: (r["support"], r["wes"]) for r in other.result.collect()}
    kept.unpersist()


def test_studies_pack_each_sequence_once(spark, monkeypatch):
    """whole and batches come from the same packed blocks; nothing is packed by a batch or for the whole again."""
    from probseq import workloads  # noqa: F401  it registers the queries first
    from probseq import increments
    from probseq.operators import encode, incremental, miner

    made, real = [], increments.in_blocks
    monkeypatch.setattr(increments, "in_blocks", lambda *x: made.append(1) or real(*x))
    for module, name in ((incremental, "packed_once"), (incremental, "dictionary"), (miner, "pack"), (encode, "pack")):
        monkeypatch.setattr(module, name, lambda *x: pytest.fail("packed or counted again"))
    study = increments.Study(increments.WORK, [[0.2, 0.6, 1.0]], increments._both([0], [0.02], [0.8]), 3, "time")
    rows = study.run(spark, "/root/testdata/sf0.001")
    assert len(made) == 1 and len(rows) == 2 and all(r[5] == r[7] <= r[6] for r in rows)


def test_tiers_pack_each_sequence_once(spark, monkeypatch):
    """the batches of one maintainer are packed together, too, and give the rows of the maintainer by itself."""
    from probseq import workloads  # noqa: F401  it registers the queries first
    from probseq import increments
    from probseq.operators import incremental
    from probseq.operators.incremental import ThreeTierMaintainer

    sf = "/root/testdata/sf0.001"
    parts, w = increments.parts_of(spark, sf, increments.WORK, increments.ENDS, "time")
    alone = ThreeTierMaintainer(MiningParams(increments.SUP, prune="exact"), IncrementParams(increments.MU, increments.GAMMA, 0.9), w, increments.state_folder(spark))
    alone.initialize(parts[0])
    for b in (1, 2):
        alone.apply(parts[b], b)
    monkeypatch.setattr(incremental, "dictionary", lambda *x: pytest.fail("counted by itself"))
    m, last = increments.maintained(spark, sf, ThreeTierMaintainer, local=0.9)
    key = lambda x: {r["pattern"]: (r["tier"], r["since_batch"], r["exact"], pytest.approx(r["wes"])) for r in x.tiers(spark, last).collect()}
    got = key(m)
    assert got and got == {k: (a, b, c, d.expected) for k, (a, b, c, d) in key(alone).items()}
