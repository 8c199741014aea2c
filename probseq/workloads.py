"""Queries over the given tables, one per method, variant, measure or operator, and their oracles.

Thresholds are fixed here; the deepest frequent pattern of each workload is known, and oracles go one level beyond it.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probseq import oracles as O
from probseq.config import MiningParams
from probseq.operators import baselines, encode, measures, postprocess, support
from probseq.operators.miner import MiningRun, mine_capped
from probseq.sources import tables, toy
from probseq.sources.uncertainty import certain, normal_probability, normal_weights

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(fn: Query) -> Query:
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return add


def r6(c: str | F.Column) -> F.Column:
    return F.round((F.col(c) if isinstance(c, str) else c) + 1e-9, 6)


def occurrences(spark: SparkSession, sf_dir: str, work: str) -> DataFrame:
    if work == "toy":
        return toy.toy_occurrences(spark)
    base = getattr(tables, work)(spark, sf_dir)
    return base if work == "vector_bins" else normal_probability(base)


def item_weights(spark: SparkSession, occ: DataFrame, work: str) -> DataFrame:
    return toy.toy_weights(spark) if work == "toy" else normal_weights(occ.select("item"))


def shown(result: DataFrame) -> DataFrame:
    return result.select("pattern", F.col("length").cast("long").alias("length"), F.col("n_events").cast("long").alias("n_events"), F.col("support").cast("long").alias("support"), r6("es").alias("es"), r6("seq_weight").alias("seq_weight"), r6("wes").alias("wes"))


def mined(spark: SparkSession, sf_dir: str, work: str, min_sup: float, weighted: bool = True, **kw) -> MiningRun:
    occ = occurrences(spark, sf_dir, work).persist()
    try:
        w = item_weights(spark, occ, work) if weighted else None
        return mine_capped(occ, w, MiningParams(min_sup, **kw))
    finally:
        occ.unpersist()


# --- miners: (name, workload, min_sup, weighted, deepest level + 1)

# Long dense sequences keep caps loose at every depth: there the exact support prunes, and a length limit ends the search.
EXACT = {"prune": "exact"}
MINERS = [
    ("mine_weighted_customer_brand", "customer_brand", 0.12, True, 3, EXACT),
    ("mine_unweighted_customer_brand", "customer_brand", 0.15, False, 3, EXACT),
    ("mine_weighted_userday", "userday_types", 0.002, True, 4, {}),
    ("mine_unweighted_userday", "userday_types", 0.002, False, 4, {}),
    ("mine_userday_clicks", "userday_clicks", 0.0005, False, 3, {}),
    ("mine_user_buckets", "user_buckets", 0.5, False, 4, EXACT),
    ("mine_sentence_words", "sentence_words", 0.003, False, 4, EXACT),
    ("mine_order_brand", "order_brand", 0.004, True, 3, {}),
    ("mine_customer_type_size", "customer_type_size", 0.12, False, 3, EXACT),
    ("mine_segment_brand_type", "segment_brand_type", 0.02, False, 3, EXACT),
    ("mine_supplier_brand", "supplier_brand", 0.9, True, 4, EXACT),
    ("mine_curated_words", "curated_words", 0.01, True, 4, EXACT),
    ("mine_dialogue", "dialogue", 0.2, True, 4, EXACT),
    ("mine_page_tags", "page_tags", 0.6, False, 3, EXACT | {"max_len": 3}),
    ("mine_vector_bins", "vector_bins", 0.5, True, 2, EXACT | {"max_len": 2}),
    ("mine_toy_weighted", "toy", 0.1, True, 4, {}),
    ("mine_toy_unweighted", "toy", 0.1, False, 4, {}),
]


def _miner(work: str, min_sup: float, weighted: bool, **kw) -> Query:
    return lambda spark, sf_dir: shown(mined(spark, sf_dir, work, min_sup, weighted, **kw).result)


for _name, _work, _sup, _weighted, _depth, _kw in MINERS:
    query(_name, O.mine(_work, _sup, _depth, weighted=_weighted))(_miner(_work, _sup, _weighted, **_kw))

_variants = {
    "mine_final_scan": {"verify": "final_scan"},
    "mine_prune_exact": {"prune": "exact"},
    "mine_cooccurring": {"i_ext": "cooccurring"},
    "mine_relational_engine": {"engine": "relational"},
    "mine_tight_global_weight": {"weight_cap": "global"},
    "mine_loose_local_weight": {"support_cap": "loose"},
    "mine_loose_global_weight": {"support_cap": "loose", "weight_cap": "global"},
}
for _name, _kw in _variants.items():
    query(_name, O.mine("userday_types", 0.002, 4))(_miner("userday_types", 0.002, True, **_kw))
# several items an event; caps stay loose on long sequences, so the length limit is the point here
for _name, _kw in (("mine_final_scan_itemsets", {"verify": "final_scan"}), ("mine_cooccurring_itemsets", {"i_ext": "cooccurring"}), ("mine_relational_itemsets", {"engine": "relational"})):
    query(_name, O.mine("user_buckets", 0.6, 2))(_miner("user_buckets", 0.6, True, max_len=2, **_kw))

# a weight factor, sequence frequencies, a length limit and a given threshold
query("mine_weight_factor", O.mine("userday_types", 0.002, 4, wgt_fct=1.5))(_miner("userday_types", 0.002, True, wgt_fct=1.5))
query("mine_max_len_dense_users", O.mine("user_types", 0.6, 2, weighted=False))(_miner("user_types", 0.6, False, max_len=2))
query("mine_sequence_frequency", O.mine("userday_types", 0.0, 4, value="0.003 * (SELECT count(DISTINCT seq_id) FROM occ) * (SELECT sum(weight) / count(*) FROM (SELECT DISTINCT seq_id, item, weight FROM occ))"))(
    _miner("userday_types", 0.003, True, freq="sequences")
)


@query("mine_given_threshold", O.mine("userday_types", 0.0, 4, value="9.5"))
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types")
    return shown(mine_capped(occ, item_weights(spark, occ, "userday_types"), MiningParams(0.0), 9.5).result)


@query("mine_precise_userday", O.mine("userday_types", 0.0, 6, weighted=False, certain=True, value="80"))
def _(spark, sf_dir):
    return shown(baselines.mine_precise(tables.userday_types(spark, sf_dir), 80).result)


@query(
    "mine_itemsets_orders",
    O.mine("order_brand", 0.0, 3, value="30", weighted=False).replace("SELECT DISTINCT l_orderkey AS seq_id, date_diff('day', DATE '1990-01-01', l_shipdate::DATE) AS pos", "SELECT DISTINCT l_orderkey AS seq_id, 1 AS pos"),
)
def _(spark, sf_dir):
    one = tables.order_brand(spark, sf_dir).select("seq_id", F.lit(1).alias("pos"), "item").distinct()
    return shown(mine_capped(normal_probability(one), None, MiningParams(0.0), 30.0).result)


@query("mine_loose_userday", O.mine("userday_types", 0.01, 3))
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types")
    return shown(baselines.mine_loose(occ, item_weights(spark, occ, "userday_types"), MiningParams(0.01)).result)


@query("mine_global_weight_userday", O.mine("userday_types", 0.002, 4))
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types")
    return shown(baselines.mine_global_weight(occ, item_weights(spark, occ, "userday_types"), MiningParams(0.002)).result)


@query(
    "mine_separate_thresholds",
    f"{O.head('userday_types')}, {O.thresholds(0, value='10.0')}, {O.levels(4)} {O.RESULT} FROM ({O.all_levels(4)}) WHERE es >= 10.0 * (1 - 1e-9) AND seq_weight >= 0.5",
)
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types")
    return shown(baselines.mine_separate(occ, item_weights(spark, occ, "userday_types"), 10.0, 0.5))


@query("mine_generate_test", O.mine("userday_types", 0.0, 4, value="9.5"))
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types").persist()
    return shown(baselines.mine_generate_test(occ, item_weights(spark, occ, "userday_types"), 9.5))


@query("mine_bruteforce", O.mine("user_buckets", 0.0, 2, value="60"))
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "user_buckets")
    return shown(baselines.mine_bruteforce(occ, item_weights(spark, occ, "user_buckets"), 60.0, 2))


@query("mine_probabilistic")
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types").persist()
    return baselines.mine_probabilistic(occ, 20, 0.9, max_len=None).select("pattern", r6("es").alias("es"), r6("probability").alias("probability"))


# --- measures


def _pairs(spark: SparkSession, items: list[str]) -> DataFrame:
    rows = [(f"<({a})({b})>",) for a in items for b in items] + [(f"<({a} {b})>",) for a in items for b in items if a < b]
    return spark.createDataFrame(rows, "pattern string")


def _names(occ: DataFrame, most: int = 100) -> list[str]:
    """The item names of a workload with a small alphabet."""
    names = sorted(r["item"] for r in occ.select("item").distinct().limit(most + 1).collect())
    if len(names) > most:
        raise ValueError("the alphabet is too large to list all pairs")
    return names


_SUPPORT = "SELECT '<' || pat || '>' AS pattern, support::BIGINT AS support, " + O.r6("es") + " AS es, " + O.r6("seq_weight") + " AS seq_weight, " + O.r6("es * seq_weight") + " AS wes"


def _supports(df: DataFrame) -> DataFrame:
    return df.where("support > 0").select("pattern", "support", r6("es").alias("es"), r6("seq_weight").alias("seq_weight"), r6("wes").alias("wes"))


def _support_query(length: int, engine: str) -> Query:
    def run(spark, sf_dir):
        occ = occurrences(spark, sf_dir, "userday_types").persist()
        names = _names(occ)
        texts = [""]
        for _ in range(length):
            texts = [f"{t}({x})" for t in texts for x in names]
        pats = spark.createDataFrame([(f"<{t}>",) for t in texts], "pattern string")
        return _supports(support.expected_support(occ, pats, item_weights(spark, occ, "userday_types"), engine))

    return run


_ALL = f"{O.head('userday_types')}, {O.levels(3, prune=False)} {_SUPPORT} FROM "
for _n in (1, 2, 3):
    query(f"expected_support_len{_n}_userday", _ALL + f"e{_n}")(_support_query(_n, "arrow"))
query("tree_support_arrow", _ALL + "e3")(_support_query(3, "arrow"))
query("tree_support_relational", _ALL + "e3")(_support_query(3, "relational"))
query("tree_support_hof", _ALL + "e2")(_support_query(2, "hof"))
query("pairwise_support", _ALL + "e2")(_support_query(2, "pairwise"))

_PAIRS = f"{O.head('user_buckets')}, {O.levels(2, prune=False)} "


def _pair_query(fn: Callable[[SparkSession, DataFrame, DataFrame, DataFrame], DataFrame], work: str = "user_buckets") -> Query:
    def run(spark, sf_dir):
        occ = occurrences(spark, sf_dir, work).persist()
        return fn(spark, occ, _pairs(spark, _names(occ)), item_weights(spark, occ, work))

    return run


query("support_count_pairs", _PAIRS + "SELECT '<' || pat || '>' AS pattern, support::BIGINT AS support FROM e2")(
    _pair_query(lambda s, occ, p, w: support.expected_support(occ, p, None).where("support > 0").select("pattern", "support"))
)
query("seq_weight_pairs", _PAIRS + f"SELECT '<' || pat || '>' AS pattern, {O.r6('seq_weight')} AS seq_weight FROM e2")(
    _pair_query(lambda s, occ, p, w: measures.seq_weight(support.expected_support(occ, p, None).where("support > 0"), w).select("pattern", r6("seq_weight").alias("seq_weight")))
)
query("wes_pairs", _PAIRS + _SUPPORT + " FROM e2")(_pair_query(lambda s, occ, p, w: _supports(support.expected_support(occ, p, w, "relational"))))
query("pairwise_joins", _PAIRS + f"SELECT '<' || pat || '>' AS pattern, support::BIGINT AS support, {O.r6('es')} AS es FROM e2")(
    _pair_query(lambda s, occ, p, w: support.pairwise_joins(occ, p, 2).select("pattern", "support", r6("es").alias("es")))
)
query("best_match_in_sequence", _PAIRS + f"SELECT seq_id, '<' || pat || '>' AS pattern, {O.r6('max(pr)')} AS best FROM l2 GROUP BY seq_id, pat")(
    _pair_query(lambda s, occ, p, w: support.max_pr_in_seq(occ, p).select("seq_id", "pattern", r6("best").alias("best")))
)
query("end_positions_pairs", _PAIRS + f"SELECT seq_id, '<' || pat || '>' AS pattern, pos, {O.r6('pr')} AS pr FROM l2")(
    _pair_query(lambda s, occ, p, w: support.end_positions(occ, p).select("seq_id", "pattern", "pos", r6("pr").alias("pr")))
)

_ITEM = f"{O.head('customer_brand')} "
query("db_weight_mean_occ", _ITEM + f"SELECT {O.r6('sum(weight) / count(*)')} AS wam FROM occ")(
    lambda s, d: measures.weight_mean(encode.dictionary(occ := occurrences(s, d, "customer_brand"), item_weights(s, occ, "customer_brand"))).select(r6("wam").alias("wam"))
)
query("db_weight_mean_seq", _ITEM + f"SELECT {O.r6('sum(weight) / count(*)')} AS wam FROM (SELECT DISTINCT seq_id, item, weight FROM occ)")(
    lambda s, d: measures.weight_mean(encode.dictionary(occ := occurrences(s, d, "customer_brand"), item_weights(s, occ, "customer_brand")), "sequences").select(r6("wam").alias("wam"))
)
query("global_weight_cap", _ITEM + "SELECT max(weight) AS w_cap_global FROM occ")(
    lambda s, d: measures.database_stats(occ := occurrences(s, d, "customer_brand"), item_weights(s, occ, "customer_brand")).select(F.col("w_max").alias("w_cap_global"))
)


@query(
    "thresholds",
    _ITEM
    + f"SELECT n_seq, {O.r6('wam')} AS wam, {O.r6('0.12 * n_seq * wam * 1.2')} AS min_wes, {O.r6('0.7 * 0.12 * n_seq * wam * 1.2')} AS min_wes_buf, {O.r6('0.8 * 0.7 * 0.12 * 300 * wam * 1.2')} AS local_wes FROM (SELECT count(DISTINCT seq_id) AS n_seq, sum(weight) / count(*) AS wam FROM occ)",
)
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "customer_brand")
    s = measures.database_stats(occ, item_weights(spark, occ, "customer_brand"))
    low = measures.global_threshold(F.col("n_seq"), F.col("wam"), 0.12, 1.2)
    return s.select("n_seq", r6("wam").alias("wam"), r6(low).alias("min_wes"), r6(measures.buffer_threshold(low, 0.7)).alias("min_wes_buf"), r6(measures.local_threshold(F.lit(300), F.col("wam"), 0.12, 0.7, 0.8, 1.2)).alias("local_wes"))


query(
    "dictionary_customer_brand",
    _ITEM + "SELECT item, weight, count(*)::BIGINT AS occ, count(DISTINCT seq_id)::BIGINT AS seqs FROM occ GROUP BY item, weight",
)(lambda s, d: encode.dictionary(occ := occurrences(s, d, "customer_brand"), item_weights(s, occ, "customer_brand")).select("item", "weight", "occ", "seqs"))

query("suffix_max_rows", f"{O.head('userday_clicks')} SELECT seq_id, pos, item, p, max(p) OVER (PARTITION BY seq_id, item ORDER BY pos DESC) AS p_sfx FROM occ0")(
    lambda s, d: encode.suffix_max(occurrences(s, d, "userday_clicks")).select("seq_id", F.col("pos").cast("long").alias("pos"), "item", "p", "p_sfx")
)

# both caps of all pairs: per sequence the best later (or co-occurring) suffix maximum of the extension
_CAPS = f"""{O.head('user_buckets')}, sfx AS (SELECT *, max(p) OVER (PARTITION BY seq_id, item ORDER BY pos DESC) AS s FROM occ),
 one AS (SELECT item, max(p) AS mx FROM occ GROUP BY item), f AS (SELECT seq_id, item, min(pos) AS e0 FROM occ GROUP BY 1, 2),
 best AS (SELECT f.item AS a, '<(' || f.item || ')(' || o.item || ')>' AS pattern, o.seq_id, max(o.s) AS b FROM f JOIN sfx o ON o.seq_id = f.seq_id AND o.pos > f.e0 GROUP BY f.item, o.item, o.seq_id
   UNION ALL SELECT x.item, '<(' || x.item || ' ' || o.item || ')>', o.seq_id, max(o.s) FROM occ x JOIN sfx o ON o.seq_id = x.seq_id AND o.pos = x.pos AND o.item > x.item GROUP BY x.item, o.item, o.seq_id),
 caps AS (SELECT pattern, any_value(mx) * max(b) AS max_pr, any_value(mx) * sum(b) AS es_cap, any_value(mx) * max(b) * count(*) AS es_cap_loose, count(*)::BIGINT AS support_rows FROM best JOIN one ON one.item = a GROUP BY pattern)"""


def _caps(*columns: str) -> Query:
    return lambda s, d: measures.pair_caps(occurrences(s, d, "user_buckets")).select("pattern", *(r6(c).alias(c) if c != "support_rows" else c for c in columns))


query("max_pr_pairs", f"{_CAPS} SELECT pattern, {O.r6('max_pr')} AS max_pr FROM caps")(_caps("max_pr"))
query("tight_cap_pairs", f"{_CAPS} SELECT pattern, {O.r6('es_cap')} AS es_cap FROM caps")(_caps("es_cap"))
query("loose_cap_pairs", f"{_CAPS} SELECT pattern, {O.r6('es_cap_loose')} AS es_cap_loose, support_rows FROM caps")(_caps("es_cap_loose", "support_rows"))


@query("cap_order_check", f"{_CAPS}, {O.levels(2, prune=False)} SELECT count(*)::BIGINT AS n, count(*) FILTER (es <= es_cap + 1e-9)::BIGINT AS es_below_tight, count(*) FILTER (es_cap <= es_cap_loose + 1e-9)::BIGINT AS tight_below_loose FROM caps JOIN e2 ON '<' || pat || '>' = pattern")
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "user_buckets").persist()
    es = support.expected_support(occ, _pairs(spark, _names(occ)), None).select("pattern", "es").where("es > 0")
    j = measures.pair_caps(occ).join(es, "pattern")
    return j.agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("es") <= F.col("es_cap") + 1e-9, 1)).alias("es_below_tight"), F.count(F.when(F.col("es_cap") <= F.col("es_cap_loose") + 1e-9, 1)).alias("tight_below_loose"))


query(
    "weight_cap_items",
    f"""{O.head('user_buckets')}, f AS (SELECT seq_id, item, weight, min(pos) AS e0 FROM occ GROUP BY 1, 2, 3),
 nxt AS (SELECT f.item, o.weight FROM f JOIN occ o ON o.seq_id = f.seq_id AND o.pos > f.e0 UNION ALL SELECT x.item, o.weight FROM occ x JOIN occ o ON o.seq_id = x.seq_id AND o.pos = x.pos AND o.item > x.item UNION ALL SELECT item, weight FROM occ)
 SELECT item, max(weight) AS w_cap, (SELECT max(weight) FROM occ) AS w_cap_global FROM nxt GROUP BY item""",
)(lambda s, d: measures.item_weight_caps(occ := occurrences(s, d, "user_buckets"), item_weights(s, occ, "user_buckets")).select("item", "w_cap", "w_cap_global"))

# --- the pattern tree

# the shape of the example tree, its items being event types
_TREE_PATTERNS = ["<(click)>", "<(view)>", "<(click view)>", "<(purchase)>", "<(view)(purchase)>", "<(signup)>", "<(purchase signup)>", "<(purchase)(signup)>"]


@query(
    "tree_fig1_arrays",
    f"""{O.head('user_buckets')},
 one AS (SELECT seq_id, '<(' || item || ')>' AS pattern, pos, p AS pr FROM occ),
 s AS (SELECT a.seq_id, '<(' || a.item || ')(' || b.item || ')>' AS pattern, b.pos, max(a.p * b.p) AS pr FROM occ a JOIN occ b ON b.seq_id = a.seq_id AND b.pos > a.pos GROUP BY 1, 2, 3),
 i AS (SELECT a.seq_id, '<(' || a.item || ' ' || b.item || ')>' AS pattern, b.pos, a.p * b.p AS pr FROM occ a JOIN occ b ON b.seq_id = a.seq_id AND b.pos = a.pos AND b.item > a.item)
 SELECT seq_id, pattern, pos, {O.r6('pr')} AS pr FROM (SELECT * FROM one UNION ALL SELECT * FROM s UNION ALL SELECT * FROM i) WHERE pattern IN (SELECT * FROM (VALUES {", ".join(f"('{p}')" for p in _TREE_PATTERNS)}))""",
)
def _(spark, sf_dir):
    """The arrays of a tree's nodes: every end of a pattern in every sequence, with the best probability there."""
    occ = occurrences(spark, sf_dir, "user_buckets").persist()
    pats = spark.createDataFrame([(p,) for p in _TREE_PATTERNS], "pattern string")
    return support.end_positions(occ, pats).select("seq_id", "pattern", "pos", r6("pr").alias("pr"))


_FOUND = O.mined("userday_types", 0.002, 4)


@query("tree_nodes", f"{_FOUND}, n AS (SELECT DISTINCT list_slice(string_split(pat[2:-2], ')('), 1, k) AS e FROM (SELECT pat, unnest(range(1, length + 1)) AS k FROM found)) SELECT '<(' || array_to_string(e, ')(') || ')>' AS node, CASE WHEN len(e) > 1 THEN '<(' || array_to_string(e[:-2], ')(') || ')>' END AS parent, len(e)::BIGINT AS depth, 'S' AS kind, e[-1] AS item FROM n")
def _(spark, sf_dir):
    found = mined(spark, sf_dir, "userday_types", 0.002).result
    return support.tree_nodes(found).select("node", "parent", F.col("depth").cast("long").alias("depth"), "kind", "item")


# --- what a user does with patterns

_POST = f"{_FOUND}, res AS (SELECT '<' || pat || '>' AS pattern, length::BIGINT AS length, es, support, seq_weight, es * seq_weight AS wes FROM found)"


def _post(fn: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda s, d: fn(mined(s, d, "userday_types", 0.002).result)


query("topk_patterns", f"{_POST} SELECT pattern, {O.r6('wes')} AS wes FROM res ORDER BY res.wes DESC, pattern LIMIT 10")(_post(lambda r: postprocess.top_k(r, 10).select("pattern", r6("wes").alias("wes"))))
query("topk_per_length", f"{_POST} SELECT length, rank::BIGINT AS rank, pattern, {O.r6('wes')} AS wes FROM (SELECT *, row_number() OVER (PARTITION BY length ORDER BY wes DESC, pattern) AS rank FROM res) WHERE rank <= 3")(
    _post(lambda r: postprocess.top_k_per_length(r, 3).select(F.col("length").cast("long").alias("length"), F.col("rank").cast("long").alias("rank"), "pattern", r6("wes").alias("wes")))
)
# patterns here have one item per event, so containment is a LIKE
_IN = "b.length > a.length AND b.pattern LIKE '%' || replace(a.pattern[2:-2], ')(', ')%(') || '%'"
query("maximal_patterns", f"{_POST} SELECT pattern FROM res a WHERE NOT EXISTS (SELECT 1 FROM res b WHERE {_IN})")(_post(lambda r: postprocess.maximal(r).select("pattern")))
query("closed_patterns", f"{_POST} SELECT pattern FROM res a WHERE NOT EXISTS (SELECT 1 FROM res b WHERE {_IN} AND round(a.es, 9) = round(b.es, 9))")(_post(lambda r: postprocess.closed(r).select("pattern")))
query(
    "sequence_rules",
    f"{_POST}, c AS (SELECT regexp_replace(pattern, '\\([^()]*\\)>$', '>') AS antecedent, '<' || regexp_extract(pattern, '(\\([^()]*\\))>$', 1) || '>' AS consequent, es FROM res WHERE length > 1) SELECT antecedent, consequent, {O.r6('c.es')} AS es, {O.r6('c.es / res.es')} AS confidence FROM c JOIN res ON res.pattern = antecedent WHERE c.es / res.es >= 0.02",
)(_post(lambda r: postprocess.rules(r, 0.02).select("antecedent", "consequent", r6("es").alias("es"), r6("confidence").alias("confidence"))))
query("select_patterns", f"{_POST} SELECT pattern, {O.r6('seq_weight')} AS seq_weight FROM res WHERE pattern LIKE '%(click)%' AND pattern LIKE '<(click)%' AND length BETWEEN 1 AND 2")(
    _post(lambda r: postprocess.select_patterns(r, item="click", first="click", lengths=(1, 2)).select("pattern", r6("seq_weight").alias("seq_weight")))
)
query("rollup_length", f"{_POST} SELECT length, n_events, count(*)::BIGINT AS n, {O.r6('sum(wes)')} AS wes FROM (SELECT *, length AS n_events FROM res) GROUP BY ROLLUP (length, n_events)")(
    _post(lambda r: r.rollup(F.col("length").cast("long").alias("length"), F.col("n_events").cast("long").alias("n_events")).agg(F.count(F.lit(1)).alias("n"), r6(F.sum("wes")).alias("wes")))
)


from probseq import experiments, increments, relational  # noqa: E402  they register more queries

__all__ = ["QUERIES", "ORACLES", "experiments", "increments", "relational"]
