"""Trees, formats, sinks, functions, streams and plans around the miners."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from probseq.config import MiningParams
from probseq.operators.miner import mine_capped
from probseq.sources import toy


@pytest.fixture(scope="module")
def db(spark):
    return toy.toy_occurrences(spark).persist(), toy.toy_weights(spark)


def test_pattern_tree(spark, db):
    from probseq.operators.tree import PatternTree

    pats = spark.createDataFrame([("<(a)(b)>", 1.0), ("<(a)(b c)(d)>", 3.0), ("<(e)>", 2.0)], "pattern string, wes double")
    tree = PatternTree.from_patterns(pats)
    rows = {r["node"]: r for r in tree.to_df().collect()}
    assert set(rows) == {"<(a)>", "<(a)(b)>", "<(a)(b c)>", "<(a)(b c)(d)>", "<(e)>"}
    assert rows["<(a)(b c)>"]["kind"] == "I" and rows["<(a)(b c)>"]["parent"] == "<(a)(b)>" and rows["<(a)>"]["value"] is None
    assert {r["pattern"] for r in tree.select(2.0).collect()} == {"<(a)(b c)(d)>", "<(e)>"}
    pruned = {r["node"]: r["value"] for r in tree.prune(2.5).to_df().collect()}
    assert pruned == {"<(a)>": None, "<(a)(b)>": None, "<(a)(b c)>": None, "<(a)(b c)(d)>": 3.0}  # inner nodes lead on, their values went
    other = PatternTree.from_patterns(spark.createDataFrame([("<(a)(b)>", 0.5), ("<(f)>", 4.0)], "pattern string, wes double"))
    both = {r["node"]: (r["value"], r["sources"]) for r in tree.merge(other).to_df().collect()}
    assert both["<(a)(b)>"] == (1.5, 2) and both["<(f)>"] == (4.0, 1) and both["<(a)>"] == (None, 2) and len(both) == 6
    found = mine_capped(*db, MiningParams(0.1)).result
    again = {r["pattern"]: r["value"] for r in PatternTree.from_patterns(found).patterns().collect()}
    assert again == {r["pattern"]: r["wes"] for r in found.collect()}


@pytest.mark.parametrize("kind", ["parquet", "orc", "json", "csv", "text"])
def test_formats(spark, db, tmp_path, kind):
    from probseq.sources.files import read_occurrences, write_occurrences

    write_occurrences(db[0], f"{tmp_path}/x", kind)
    ids = kind != "text"  # that format has none
    key = lambda d: sorted((r["seq_id"] * ids, r["pos"], r["item"], r["p"]) for r in d.collect())
    back = read_occurrences(spark, f"{tmp_path}/x", kind)
    assert key(back) == key(db[0]) and back.select("seq_id").distinct().count() == 6
    with pytest.raises(ValueError):
        read_occurrences(spark, "x", "xml")


def test_sinks(spark, db, tmp_path):
    from probseq.sources import sinks

    rows = spark.createDataFrame([("<(a)>", 1.0, 0), ("<(b)>", 2.0, 1)], "pattern string, wes double, batch_id int")
    sinks.write_versions(rows, f"{tmp_path}/v")
    sinks.write_versions(rows.where("batch_id = 1").withColumn("wes", F.lit(5.0)), f"{tmp_path}/v")
    assert {(r["pattern"], r["wes"]) for r in spark.read.parquet(f"{tmp_path}/v").collect()} == {("<(a)>", 1.0), ("<(b)>", 5.0)}
    sinks.write_bucketed(db[0], "occ_buckets", 4)
    t = spark.table("occ_buckets")
    plan = t.groupBy("seq_id").count()._jdf.queryExecution().executedPlan().toString()
    assert t.count() == db[0].count() and "Exchange" not in plan
    spark.sql("DROP TABLE occ_buckets")


def test_support_aggregate(spark, db):
    from probseq.functions.aggregates import expected_support_by
    from probseq.operators.support import expected_support

    for pattern in ("<(a)(b)>", "<(a c)(a)>", "<(c)(a)(d)>", "<(g)(x)>"):
        got = expected_support_by(db[0], pattern, F.lit(1).alias("one")).first()
        want = expected_support(db[0], spark.createDataFrame([(pattern,)], "pattern string")).first()
        assert got["es"] == pytest.approx(want["es"]) and got["support"] == want["support"]
    halves = {r["half"]: r["es"] for r in expected_support_by(db[0], "<(a)(b)>", (F.col("seq_id") > 3).alias("half")).collect()}
    assert halves == pytest.approx({False: 0.54, True: 0.03})


def test_probabilities(spark, db):
    from probseq.sources.uncertainty import price_weights, quantity_probability, random_probability

    base = spark.range(20000).select(F.col("id").alias("seq_id"), F.lit(1).alias("pos"), F.lit("a").alias("item"))
    a, b = random_probability(base), random_probability(base.repartition(7))
    s = a.agg(F.avg("p").alias("m"), F.stddev("p").alias("sd"), F.min("p").alias("lo"), F.max("p").alias("hi")).first()
    assert s["m"] == pytest.approx(0.5, abs=0.01) and s["sd"] == pytest.approx(0.25, abs=0.02) and s["lo"] >= 0.01 and s["hi"] <= 1
    assert a.exceptAll(b).count() == 0
    q = quantity_probability(spark.createDataFrame([(1, 1, "a", 0.0), (1, 2, "a", 50.0), (1, 3, "a", 80.0)], "seq_id long, pos int, item string, q double"), "q", 50)
    assert [r["p"] for r in q.orderBy("pos").collect()] == pytest.approx([0.95, 0.05, 0.01])
    part = spark.createDataFrame([("x", 10.0), ("x", 30.0), ("y", 40.0)], "b string, p_retailprice double")
    assert {r["item"]: r["weight"] for r in price_weights(part, F.col("b")).collect()} == {"x": 0.5, "y": 1.0}


def test_threshold_for_a_number_of_patterns(db):
    from probseq.operators.postprocess import sample_sequences, threshold_for

    low, result = threshold_for(*db, 5, MiningParams(0.0, max_len=3))
    assert result.count() >= 5 and mine_capped(*db, MiningParams(0.0, max_len=3), low).n_frequent == result.count()
    with pytest.raises(ValueError):
        threshold_for(*db, 10_000, MiningParams(0.0, max_len=1), rounds=3)
    assert sample_sequences(db[0], 1.0).count() == db[0].count() and sample_sequences(db[0], 0.0).count() == 0


def test_ranks_without_one_task(spark):
    from probseq.operators.splits import ranked, tile

    rows = spark.createDataFrame([(k * k - 50,) for k in range(103)], "k long")
    got = {r["k"]: (r["rank"], r["t"]) for r in ranked(rows, "k", 16).select("k", "rank", tile(F.col("rank"), F.col("total"), 5).alias("t")).collect()}
    want = {r["k"]: r["t"] for r in rows.selectExpr("k", "ntile(5) over (order by k) t").collect()}
    assert {k: t for k, (_, t) in got.items()} == want and sorted(n for n, _ in got.values()) == list(range(103))
    assert ranked(rows.limit(0), "k").count() == 0


def test_kernel_ways_agree():
    """Statistics by matrix and by list, in one batch and in many."""
    import numpy as np

    from probseq.operators import kernel

    r = np.random.default_rng(0)
    lengths, pos, item, p = [], [], [], []
    for _ in range(40):
        rows = sorted({(int(r.integers(0, 9)), int(r.integers(0, 6))) for _ in range(int(r.integers(0, 25)))})
        lengths.append(len(rows))
        pos += [a for a, _ in rows]
        item += [b for _, b in rows]
        p += r.uniform(0.05, 1, len(rows)).tolist()
    args = np.array(lengths), np.array(pos, np.int32), np.array(item, np.int32), np.array(p)
    batch = kernel.Batch(*args, 6)
    first = batch.child(None, "S", 2)
    for node, last in ((None, -1), (first, 2), (batch.child(first, "S", 1), 1), (batch.child(first, "I", 4), 4)):
        for cooccurring in (False, True):
            def flat(found):
                return {(k, int(i)): (m, s, c) for k, *cols in found for i, m, s, c in zip(*(np.asarray(x).tolist() for x in cols), strict=True)}

            a = flat(batch.extensions(node, last, cooccurring))
            b = flat(batch._by_list(node, last, cooccurring))
            assert set(a) == set(b) and all(a[k] == pytest.approx(b[k]) for k in a)
    kernel.GATHER, kept = 12, kernel.GATHER
    small = flat(batch.extensions(first, 2, False))
    kernel.GATHER = kept
    whole = flat(batch.extensions(first, 2, False))
    assert set(small) == set(whole) and all(small[k] == pytest.approx(whole[k]) for k in small)


# --- streams


def events(spark, tmp_path):
    """Two users, three days, one row again and one row late; files in order of time."""
    at = lambda day, minute: dt.datetime(2024, 1, day, 0, minute)
    rows = [
        [(1, 1, at(1, 0), "a"), (2, 1, at(1, 10), "b"), (3, 2, at(1, 5), "a"), (2, 1, at(1, 10), "b")],
        [(4, 1, at(2, 0), "a"), (5, 2, at(2, 20), "b"), (6, 2, at(2, 25), "a")],
        [(7, 1, at(9, 0), "z"), (8, 2, at(9, 0), "z")],  # moves the watermark past everything before
        [(12, 1, at(10, 0), "z")],  # a row is late against the watermark of the batch before
        [(9, 1, at(1, 30), "late")],
        [(10, 1, at(20, 0), "z"), (11, 2, at(20, 0), "z")],
    ]
    schema = "event_id long, user_id long, ts timestamp_ntz, event_type string"
    for k, own in enumerate(rows):
        spark.createDataFrame(own, schema).coalesce(1).write.parquet(f"{tmp_path}/in/b{k}")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"{tmp_path}/in")


def run(df, name, tmp_path):
    q = df.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", f"{tmp_path}/ck-{name}").trigger(availableNow=True).start()
    q.awaitTermination(240)
    return q


def test_streams_equal_their_batch_twins(spark, tmp_path):
    from probseq.streaming import increments as S

    timed = S.without_repeats(S.timed_events(events(spark, tmp_path)))
    run(S.sessions(timed, "30 minutes"), "sessions", tmp_path)
    got = {(r["user_id"], r["start"].day): [e["event_type"] for e in r["events"]] for r in spark.table("sessions").collect()}
    assert got[1, 1] == ["a", "b"] and got[2, 1] == ["a"] and got[1, 2] == ["a"] and got[2, 2] == ["b", "a"]
    q = run(S.days(S.timed_events(events_again(spark, tmp_path))), "days", tmp_path)
    got = {(r["user_id"], r["start"].day): [e["event_type"] for e in r["events"]] for r in spark.table("days").collect()}
    assert got[1, 1] == ["a", "b", "b"] and got[2, 2] == ["b", "a"] and S.dropped_rows(q) >= 1  # the late row never comes
    run(S.sliding(S.timed_events(events_again(spark, tmp_path))), "sliding", tmp_path)
    batch = spark.read.parquet(*[f"{tmp_path}/in/b{k}" for k in (0, 1, 2, 3, 5)]).withColumn("ts", F.col("ts").cast("timestamp"))
    want = {(r["user_id"], r["start"]): r["events"] for r in S.sliding(batch).collect() if r["start"] < dt.datetime(2024, 1, 19)}
    assert {(r["user_id"], r["start"]): r["events"] for r in spark.table("sliding").collect() if r["start"] < dt.datetime(2024, 1, 19)} == want


def events_again(spark, tmp_path):
    schema = "event_id long, user_id long, ts timestamp_ntz, event_type string"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"{tmp_path}/in")


def test_stream_static_join_and_late_rows(spark, tmp_path, db):
    from probseq.streaming import increments as S

    stream = events(spark, tmp_path)
    weights = spark.createDataFrame([("a", 0.5), ("b", 1.0)], "item string, weight double")
    joined = S.with_weights(stream.select(F.col("user_id").alias("seq_id"), F.col("event_type").alias("item")), weights)
    run(joined, "weighted", tmp_path)
    assert {(r["item"], r["weight"]) for r in spark.table("weighted").distinct().collect()} == {("a", 0.5), ("b", 1.0), ("z", None), ("late", None)}
    batch = spark.read.parquet(*[f"{tmp_path}/in/b{k}" for k in range(6)]).withColumn("ts", F.col("ts").cast("timestamp"))
    late, timely = S.late_and_timely(batch, F.lit("2024-01-02").cast("timestamp"))
    assert (late.count(), timely.count()) == (5, 8)
    occ = S.as_occurrences(S.days(batch.dropDuplicates(["event_id"])))
    rows = sorted((r["pos"], r["item"], r["p"]) for r in occ.collect())
    assert len(rows) == 12 and max(p for p, _, _ in rows) == 3


def test_rate_stream(spark, tmp_path):
    """A soak test in small: rows at a rate become occurrences of growing sequences."""
    from probseq.streaming.increments import growing_support

    rate = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", 50).option("numPartitions", 2).load()
    occ = rate.select((F.col("value") % 5).alias("seq_id"), (F.col("value") / 5).cast("int").alias("pos"), F.when(F.col("value") % 2 == 0, "a").otherwise("b").alias("item"), F.lit(0.5).alias("p"))
    q = growing_support(occ, [[["a"], ["b"]]]).writeStream.format("memory").queryName("soak").option("checkpointLocation", f"{tmp_path}/ck").start()
    try:
        for _ in range(600):
            if len([p for p in q.recentProgress if p["numInputRows"]]) >= 2:
                break
            q.awaitTermination(0.2)
    finally:
        q.stop()
    assert q.exception() is None and spark.sql("SELECT sum(change) AS es FROM soak").first()["es"] == pytest.approx(1.25)
