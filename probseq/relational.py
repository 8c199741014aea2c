"""Relational operators around sequences: set operations, joins over order and time, windows, sessions, packed forms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from probseq import oracles as O
from probseq.functions.aggregates import expected_support_by
from probseq.increments import state_folder
from probseq.operators import encode, evaluate, postprocess
from probseq.operators.splits import ranked, tile
from probseq.operators.tree import PatternTree
from probseq.sources import tables
from probseq.sources.files import FORMATS, read_occurrences, write_occurrences
from probseq.sources.uncertainty import price_weights, quantity_probability
from probseq.workloads import _FOUND, mined, occurrences, query, r6

# --- sets of patterns of two thresholds

_TWO = O.mined("userday_types", 0.002, 4) + ", tight AS (SELECT * FROM found WHERE es * seq_weight >= 2.0 * (SELECT t FROM thr) * (1 - 1e-9) OR length = 1)"


def _two(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    run = mined(spark, sf_dir, "userday_types", 0.002)
    strict = run.result.where((F.col("wes") >= 2.0 * run.threshold * (1 - 1e-9)) | (F.col("length") == 1)).select("pattern")
    return run.result.select("pattern"), strict


query("union_methods", f"{_TWO} SELECT '<' || pat || '>' AS pattern FROM found UNION SELECT '<' || pat || '>' FROM tight")(lambda s, d: (t := _two(s, d))[0].union(t[1]).distinct())
query("intersect_methods", f"{_TWO} SELECT '<' || pat || '>' AS pattern FROM found INTERSECT SELECT '<' || pat || '>' FROM tight")(lambda s, d: (t := _two(s, d))[0].intersect(t[1]))
query("except_methods", f"{_TWO} SELECT '<' || pat || '>' AS pattern FROM found EXCEPT SELECT '<' || pat || '>' FROM tight")(lambda s, d: (t := _two(s, d))[0].exceptAll(t[1]))


@query("grouping_sets_workload", f"{_FOUND} SELECT length::BIGINT AS length, left(pat, position(')' IN pat)) AS first_event, count(*)::BIGINT AS n FROM found GROUP BY GROUPING SETS ((length), (left(pat, position(')' IN pat))), ())")
def _(spark, sf_dir):
    r = mined(spark, sf_dir, "userday_types", 0.002).result
    r.select(F.col("length").cast("long").alias("length"), F.regexp_extract("pattern", r"^<(\([^)]*\))", 1).alias("first_event")).createOrReplaceTempView("probseq_found")
    return spark.sql("SELECT length, first_event, count(*) AS n FROM probseq_found GROUP BY GROUPING SETS ((length), (first_event), ())")


@query("patterns_by_tier_pivot", f"{_FOUND} SELECT length::BIGINT AS length, count(*) FILTER (seq_weight < 0.5)::BIGINT AS light, count(*) FILTER (seq_weight >= 0.5)::BIGINT AS heavy FROM found GROUP BY length")
def _(spark, sf_dir):
    r = mined(spark, sf_dir, "userday_types", 0.002).result
    kind = F.when(F.col("seq_weight") < 0.5, "light").otherwise("heavy")
    return r.withColumn("k", kind).groupBy(F.col("length").cast("long").alias("length")).pivot("k", ["light", "heavy"]).count().na.fill(0, ["light", "heavy"])


# --- joins over order and time


@query("gap_limited_pairs", f"{O.head('userday_types')} SELECT a.item AS a, b.item AS b, count(*)::BIGINT AS n, {O.r6('sum(a.p * b.p)')} AS weight FROM occ0 a JOIN occ0 b ON a.seq_id = b.seq_id AND b.pos BETWEEN a.pos + 1 AND a.pos + 2 GROUP BY 1, 2")
def _(spark, sf_dir):
    o = occurrences(spark, sf_dir, "userday_types")
    # a gap of g events is g equi-joins by shifted position: no range join
    steps = F.explode(F.array(F.lit(1), F.lit(2)))
    a = o.select("seq_id", "pos", F.col("item").alias("a"), F.col("p").alias("pa"), steps.alias("g")).select("seq_id", (F.col("pos") + F.col("g")).alias("pos"), "a", "pa")
    return a.join(o, ["seq_id", "pos"]).groupBy("a", F.col("item").alias("b")).agg(F.count(F.lit(1)).alias("n"), r6(F.sum(F.col("pa") * F.col("p"))).alias("weight"))


@query("interval_pairs", "SELECT a.event_type AS a, b.event_type AS b, count(*)::BIGINT AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR GROUP BY 1, 2")
def _(spark, sf_dir):
    e = tables.table(spark, sf_dir, "events").select("user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    w = 2 * 3600 * 1_000_000
    # both of a pair lie in the same or the next two-hour bucket: an equi-join, then the exact test
    left = e.select("user_id", F.col("event_type").alias("a"), F.col("t").alias("ta"), F.explode(F.array(F.floor(F.col("t") / w), F.floor(F.col("t") / w) + 1)).alias("bucket"))
    right = e.select("user_id", F.col("event_type").alias("b"), F.col("t").alias("tb"), F.floor(F.col("t") / w).alias("bucket"))
    return left.join(right, ["user_id", "bucket"]).where((F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + w)).groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))


@query(
    "asof_order_event",
    """WITH x AS (SELECT o_custkey AS k, o_orderkey AS id, o_orderdate AS t FROM orders WHERE o_orderpriority = '1-URGENT'), y AS (SELECT o_custkey AS k, o_orderkey AS id, o_orderdate AS t FROM orders WHERE o_orderpriority <> '1-URGENT')
 SELECT x.id AS orderkey, (SELECT y.id FROM y WHERE y.k = x.k AND y.t <= x.t ORDER BY y.t DESC, y.id DESC LIMIT 1) AS before FROM x""",
)
def _(spark, sf_dir):
    """The last other order up to each urgent one: one window over both, no join."""
    o = tables.table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", "o_orderdate", (F.col("o_orderpriority") == "1-URGENT").alias("urgent"))
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", F.col("urgent").cast("int"), "o_orderkey").rowsBetween(Window.unboundedPreceding, -1)
    other = F.when(~F.col("urgent"), F.col("o_orderkey"))
    return o.withColumn("before", F.last(other, ignorenulls=True).over(w)).where("urgent").select(F.col("o_orderkey").alias("orderkey"), "before")


query("curated_documents", f"SELECT doc_id FROM ({O.CURATED})")(lambda s, d: tables.curated_documents(s, d).select("doc_id"))


@query(
    "supplier_patterns_by_region",
    "SELECT r_name AS region, p_brand AS item, count(DISTINCT l_suppkey)::BIGINT AS sequences, count(*)::BIGINT AS lines FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey JOIN part ON p_partkey = l_partkey GROUP BY ROLLUP (r_name, p_brand)",
)
def _(spark, sf_dir):
    t = lambda n: tables.table(spark, sf_dir, n)
    s = t("supplier").join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("s_suppkey").alias("l_suppkey"), F.col("r_name").alias("region"))
    line = t("lineitem").select("l_suppkey", "l_partkey").join(s, "l_suppkey").join(t("part").select(F.col("p_partkey").alias("l_partkey"), F.col("p_brand").alias("item")), "l_partkey")
    return line.rollup("region", "item").agg(F.countDistinct("l_suppkey").alias("sequences"), F.count(F.lit(1)).alias("lines"))


# --- windows in batch form; probseq.streaming has the same as streams

query("tumbling_sequences", "SELECT user_id, date_trunc('day', ts) AS day, count(*)::BIGINT AS events, count(DISTINCT event_type)::BIGINT AS types FROM events GROUP BY 1, 2")(
    lambda s, d: tables.table(s, d, "events").groupBy("user_id", F.date_trunc("day", F.col("ts").cast("timestamp")).cast("timestamp_ntz").alias("day")).agg(F.count(F.lit(1)).alias("events"), F.countDistinct("event_type").alias("types"))
)


@query(
    "session_sequences",
    """WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 4 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
 SELECT user_id, min(ts) AS start, count(*)::BIGINT AS events FROM s GROUP BY user_id, k""",
)
def _(spark, sf_dir):
    e = tables.table(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    s = e.groupBy("user_id", F.session_window("ts", "4 hours").alias("w")).agg(F.count(F.lit(1)).alias("events"))
    return s.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "events")


@query("sliding_sequences", "SELECT epoch_us(w)::BIGINT AS start_us, count(*)::BIGINT AS events, count(DISTINCT user_id)::BIGINT AS users FROM (SELECT user_id, unnest([time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 6 HOUR * k FOR k IN range(4)]) AS w FROM events) GROUP BY 1")
def _(spark, sf_dir):
    e = tables.table(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    s = e.groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("events"), F.countDistinct("user_id").alias("users"))
    return s.select(F.unix_micros("w.start").alias("start_us"), "events", "users")


@query("late_rows", "WITH m AS (SELECT event_id, ts, max(ts) OVER (ORDER BY event_id * 7919 % 10007, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM events) SELECT event_id, ts < seen - INTERVAL 1 DAY AS late FROM m WHERE seen IS NOT NULL")
def _(spark, sf_dir):
    """Which rows of a shuffled arrival would come behind a watermark of one day.

    The maximum so far takes two steps: over whole blocks of the arrival, of which there are at most 10007, then within each block.
    """
    e = tables.table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), (F.col("event_id") * 7919 % 10007).alias("block"))
    earlier = Window.orderBy(F.asc_nulls_last("b")).rowsBetween(Window.unboundedPreceding, -1)
    blocks = e.groupBy(F.col("block").alias("b")).agg(F.max("ts").alias("top")).select("b", F.max("top").over(earlier).alias("top"))
    own = Window.partitionBy("block").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = e.withColumn("own", F.max("ts").over(own)).join(F.broadcast(blocks), F.col("block").eqNullSafe(F.col("b"))).withColumn("seen", F.greatest("own", "top"))
    return seen.where("seen is not null").select("event_id", (F.col("ts") < F.col("seen") - F.expr("interval 1 day")).alias("late"))


@query("json_items", "SELECT event_type || (json_extract(props, '$.k')::INT // 10)::VARCHAR AS item, count(*)::BIGINT AS n FROM events GROUP BY 1")
def _(spark, sf_dir):
    k = F.from_json("props", "k int")["k"]
    return tables.table(spark, sf_dir, "events").select(F.concat("event_type", F.floor(k / 10).cast("string")).alias("item")).groupBy("item").agg(F.count(F.lit(1)).alias("n"))


@query("map_packed_event", f"{O.head('user_buckets')} SELECT seq_id, count(DISTINCT pos)::BIGINT AS events, count(*)::BIGINT AS items, {O.r6('sum(p)')} AS p FROM occ0 GROUP BY seq_id")
def _(spark, sf_dir):
    m = encode.packed_maps(occurrences(spark, sf_dir, "user_buckets"))
    total = F.aggregate("events", F.lit(0.0), lambda a, e: a + F.aggregate(F.map_values(e["items"]), F.lit(0.0), lambda x, y: x + y))
    items = F.aggregate("events", F.lit(0), lambda a, e: a + F.size(F.map_keys(e["items"])))
    return m.select("seq_id", F.size("events").cast("long").alias("events"), items.cast("long").alias("items"), r6(total).alias("p"))


@query("noisy_or_merge", f"{O.head('userday_types')} SELECT seq_id, item, {O.r6('1 - exp(sum(ln(1 - least(p, 1 - 1e-16))))')} AS p FROM occ0 GROUP BY seq_id, item")
def _(spark, sf_dir):
    o = occurrences(spark, sf_dir, "userday_types").withColumn("pos", F.lit(1))
    return encode.merge(o, "noisy_or").select("seq_id", "item", r6("p").alias("p"))


@query("rejected_rows", f"{O.head('userday_clicks')}, bad AS (SELECT seq_id, pos, item, CASE WHEN p < 0.02 THEN 0.0 ELSE p END AS p FROM occ0) SELECT seq_id, pos, item, p, 'probability' AS reason FROM bad WHERE p <= 0")
def _(spark, sf_dir):
    o = occurrences(spark, sf_dir, "userday_clicks").withColumn("p", F.when(F.col("p") < 0.02, F.lit(0.0)).otherwise(F.col("p")))
    return encode.faults(o).select("seq_id", F.col("pos").cast("long").alias("pos"), "item", "p", "reason")


@query("suffix_ntile", f"{O.head('userday_types')} SELECT seq_id, ntile(5) OVER (ORDER BY seq_id)::BIGINT AS tile FROM (SELECT DISTINCT seq_id FROM occ0)")
def _(spark, sf_dir):
    s = occurrences(spark, sf_dir, "userday_types").select("seq_id").distinct()
    return ranked(s, "seq_id").select("seq_id", tile(F.col("rank"), F.col("total"), 5).alias("tile"))


# --- the tree as a table


def _prefixes(found: str) -> str:
    return f"(SELECT DISTINCT list_slice(string_split(pat[2:-2], ')('), 1, k) AS e FROM (SELECT pat, unnest(range(1, length + 1)) AS k FROM {found}))"


_NODE = "'<(' || array_to_string(e, ')(') || ')>' AS node, len(e)::BIGINT AS depth"


@query("tree_merged", f"{_FOUND}, short AS (SELECT * FROM found WHERE length <= 2), heavy AS (SELECT * FROM found WHERE seq_weight >= 0.5) SELECT {_NODE}, count(*)::BIGINT AS sources FROM (SELECT * FROM {_prefixes('short')} UNION ALL SELECT * FROM {_prefixes('heavy')}) GROUP BY e")
def _(spark, sf_dir):
    """Two sources of patterns in one tree: short ones, and heavy ones."""
    found = mined(spark, sf_dir, "userday_types", 0.002).result
    tree = PatternTree.from_patterns(found.where("length <= 2")).merge(PatternTree.from_patterns(found.where("seq_weight >= 0.5")))
    return tree.to_df().select("node", F.col("depth").cast("long").alias("depth"), F.col("sources").cast("long").alias("sources"))


@query("tree_pruned", f"{_FOUND}, high AS (SELECT * FROM found WHERE seq_weight >= 0.52) SELECT {_NODE}, ('(' || array_to_string(e, ')(') || ')') IN (SELECT pat FROM high) AS kept FROM {_prefixes('high')}")
def _(spark, sf_dir):
    """False candidates go, inner nodes that lead to kept ones stay. The value here is the weight, which does not fall along a path."""
    found = mined(spark, sf_dir, "userday_types", 0.002).result
    tree = PatternTree.from_patterns(found, "seq_weight").prune(0.52)
    return tree.to_df().select("node", F.col("depth").cast("long").alias("depth"), F.col("value").isNotNull().alias("kept"))


# --- aggregates, samples, sources


@query("support_by_group", f"{O.head('userday_types')}, {O.levels(2, prune=False)} SELECT g::BIGINT AS part, count(*)::BIGINT AS support, {O.r6('sum(best)')} AS es FROM (SELECT seq_id % 3 AS g, seq_id, max(pr) AS best FROM l2 WHERE pat = '(click)(view)' GROUP BY seq_id) GROUP BY g")
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types")
    return expected_support_by(occ, "<(click)(view)>", (F.col("seq_id") % 3).alias("part")).select("part", "support", r6("es").alias("es"))


@query("approximate_aggregates", f"{O.head('customer_brand')} SELECT seq_id % 7 AS part, count(DISTINCT item)::BIGINT AS items, quantile_disc(p, 0.5) AS median FROM occ0 GROUP BY 1")
def _(spark, sf_dir):
    """Sketches in place of exact distinct counts and quantiles; small alphabets and enough accuracy make them exact here."""
    o = occurrences(spark, sf_dir, "customer_brand")
    return o.groupBy((F.col("seq_id") % 7).alias("part")).agg(F.approx_count_distinct("item", 0.01).alias("items"), F.percentile_approx("p", 0.5, 1_000_000).alias("median"))


@query("sampled_sequences", f"{O.head('userday_types')} SELECT seq_id, count(*)::BIGINT AS n FROM occ0 WHERE (('0x' || substr(md5('sample0|' || seq_id::VARCHAR), 1, 4))::INT / 65536.0) < 0.1 GROUP BY seq_id")
def _(spark, sf_dir):
    return postprocess.sample_sequences(occurrences(spark, sf_dir, "userday_types"), 0.1).groupBy("seq_id").agg(F.count(F.lit(1)).alias("n"))


@query("weights_from_prices", f"SELECT p_brand AS item, {O.r6('avg(p_retailprice) / max(avg(p_retailprice)) OVER ()')} AS weight FROM part GROUP BY p_brand")
def _(spark, sf_dir):
    return price_weights(tables.table(spark, sf_dir, "part"), F.col("p_brand")).select("item", r6("weight").alias("weight"))


@query("probability_from_quantity", f"SELECT l_orderkey AS seq_id, date_diff('day', DATE '1990-01-01', l_shipdate::DATE)::BIGINT AS pos, p_brand AS item, {O.r6('max(least(1.0, greatest(0.01, 0.05 + 0.9 * (1 - l_quantity / 50))))')} AS p FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1, 2, 3")
def _(spark, sf_dir):
    part = tables.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), F.col("p_brand").alias("item"))
    line = tables.table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_shipdate", "l_quantity").join(part, "l_partkey")
    day = F.datediff("l_shipdate", F.lit("1990-01-01").cast("date")).cast("long")
    occ = quantity_probability(line.select(F.col("l_orderkey").alias("seq_id"), day.alias("pos"), "item", "l_quantity"), "l_quantity", 50)
    return encode.merge(occ).select("seq_id", "pos", "item", r6("p").alias("p"))


@query("format_round_trips", f"{O.head('userday_types')} SELECT kind, count(*)::BIGINT AS n, count(DISTINCT seq_id)::BIGINT AS sequences, {O.r6('sum(p)')} AS p FROM occ0, (VALUES ('parquet'), ('orc'), ('json'), ('csv'), ('text')) t(kind) GROUP BY kind")
def _(spark, sf_dir):
    """Occurrences written in every format and read back with the schema given."""
    occ = occurrences(spark, sf_dir, "userday_types").persist()
    folder, out = state_folder(spark), None
    for kind in FORMATS:
        write_occurrences(occ, f"{folder}/{kind}", kind)
        back = read_occurrences(spark, f"{folder}/{kind}", kind).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("seq_id").alias("sequences"), r6(F.sum("p")).alias("p")).select(F.lit(kind).alias("kind"), "n", "sequences", "p")
        out = back if out is None else out.unionByName(back)
    return out


@query("quality_of_methods", f"{O.candidates('userday_types', [(0.02, 'tight', 'local'), (0.02, 'loose', 'local')], 7, False)} SELECT round(({' + '.join(f'(SELECT count(*) FROM c1_{d})' for d in range(1, 8))})::DOUBLE / ({' + '.join(f'(SELECT count(*) FROM c0_{d})' for d in range(1, 8))}), 6) AS candidate_ratio, 0::BIGINT AS missed, 100.0::DOUBLE AS precision")
def _(spark, sf_dir):
    """How many more candidates the loose cap has, and what the tight one misses of it: nothing."""
    tight, loose = (mined(spark, sf_dir, "userday_types", 0.02, False, support_cap=c) for c in ("tight", "loose"))
    missed = evaluate.false_negatives(tight.result, loose.result).agg(F.count(F.lit(1)).alias("missed"))
    right = evaluate.precision(tight.result, loose.result).select(F.round("pct", 6).alias("precision"))
    return missed.crossJoin(right).select(F.lit(round(evaluate.candidate_ratio(tight, loose), 6)).alias("candidate_ratio"), "missed", "precision")
