"""Oracle SQL for DuckDB, written apart from the engine: plain joins over levels, no caps and no suffix maxima."""

from __future__ import annotations

R6 = "round({} + 1e-9, 6)"  # products of two-digit numbers fall on ties of the sixth digit; both sides move off them


def r6(x: str) -> str:
    return R6.format(x)


def deviate(key: str) -> str:
    return f"((list_sum(list_transform(range(12), lambda k: ('0x' || substr(md5({key}), (k * 2 + 1)::INT, 2))::INT)) - 1530) / 255.998)"


def clipped(key: str, sd: float) -> str:
    return f"round(least(1.0, greatest(0.01, 0.5 + {sd} * {deviate(key)})), 2)"


_ORDERS = "SELECT o_custkey AS seq_id, o_orderkey AS orderkey, o_orderdate AS date, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS pos FROM orders"


def _lines(item: str) -> str:
    return f"SELECT DISTINCT l_orderkey AS orderkey, {item} AS item FROM lineitem JOIN part ON p_partkey = l_partkey"


def _sentences(docs: str) -> str:
    return f"""SELECT seq_id, k AS pos, words[k] AS item FROM (
      SELECT seq_id, words, unnest(range(1, len(words) + 1)) AS k FROM (
        SELECT doc_id * 2147483648 + s - 1 AS seq_id, list_filter(regexp_split_to_array(parts[s], '[^a-z]+'), lambda x: x <> '') AS words FROM (
          SELECT doc_id, parts, unnest(range(1, len(parts) + 1)) AS s FROM (SELECT doc_id, regexp_split_to_array(lower(text), '[.!?\\n]') AS parts FROM ({docs})))))"""


CURATED = """SELECT d.doc_id, d.text FROM documents d WHERE d.lang = 'en' AND d.doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)
  AND d.doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1) AND NOT EXISTS (SELECT 1 FROM benchmark b WHERE b.text = d.text)"""

BASE = {
    "customer_brand": f"SELECT seq_id, pos, item FROM ({_ORDERS}) JOIN ({_lines('p_brand')}) USING (orderkey)",
    "customer_type_size": f"SELECT seq_id, pos, item FROM ({_ORDERS}) JOIN ({_lines('p_type || (p_size // 10)::VARCHAR')}) USING (orderkey)",
    "segment_brand_type": f"SELECT seq_id, pos, item FROM ({_ORDERS}) JOIN ({_lines('p_brand || p_type')}) USING (orderkey) WHERE seq_id IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'MACHINERY')",
    "order_brand": "SELECT DISTINCT l_orderkey AS seq_id, date_diff('day', DATE '1990-01-01', l_shipdate::DATE) AS pos, p_brand AS item FROM lineitem JOIN part ON p_partkey = l_partkey",
    "supplier_brand": "SELECT DISTINCT l_suppkey AS seq_id, year(l_shipdate) * 12 + month(l_shipdate) AS pos, p_brand AS item FROM lineitem JOIN part ON p_partkey = l_partkey",
    "user_types": "SELECT user_id AS seq_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos, event_type AS item FROM events",
    "userday_types": "SELECT user_id * 100000 + date_diff('day', DATE '1970-01-01', ts::DATE) AS seq_id, row_number() OVER (PARTITION BY user_id * 100000 + date_diff('day', DATE '1970-01-01', ts::DATE) ORDER BY ts, event_id) AS pos, event_type AS item FROM events",
    "userday_clicks": "SELECT user_id * 100000 + date_diff('day', DATE '1970-01-01', ts::DATE) AS seq_id, row_number() OVER (PARTITION BY user_id * 100000 + date_diff('day', DATE '1970-01-01', ts::DATE) ORDER BY ts, event_id) AS pos, event_type || (json_extract(props, '$.k')::INT // 10)::VARCHAR AS item FROM events",
    "user_buckets": "SELECT DISTINCT user_id AS seq_id, date_diff('day', DATE '1970-01-01', ts::DATE) * 4 + hour(ts) // 6 AS pos, event_type AS item FROM events",
    "sentence_words": _sentences("SELECT doc_id, text FROM documents WHERE lang = 'en'"),
    "curated_words": _sentences(CURATED),
    "dialogue": """SELECT DISTINCT seq_id, pos, unnest(list_prepend('@' || role, w)) AS item FROM (SELECT conv_id AS seq_id, turn AS pos, role, list_filter(regexp_split_to_array(lower(text), '[^a-z]+'), lambda x: x <> '') AS w FROM conversations)""",
    "page_tags": """SELECT seq_id, k AS pos, lower(t[k]) AS item FROM (SELECT seq_id, t, unnest(range(1, len(t) + 1)) AS k FROM (SELECT page_id AS seq_id, regexp_extract_all(html, '<([a-zA-Z][a-zA-Z0-9]*)', 1) AS t FROM pages))""",
}

# The example database, one row per occurrence, and its weights.
TOY = """SELECT * FROM (VALUES (1,1,'a',.9),(1,1,'c',.6),(1,2,'a',.7),(1,3,'b',.3),(1,4,'d',.7),(2,1,'a',.6),(2,1,'c',.4),(2,2,'a',.5),(2,3,'a',.4),(2,3,'b',.3),
  (3,1,'a',.3),(3,2,'a',.2),(3,2,'b',.2),(3,3,'a',.4),(3,3,'b',.3),(3,3,'g',.5),(4,1,'a',.1),(4,1,'c',.1),(4,2,'a',.3),(4,2,'b',.1),(4,2,'c',.4),
  (5,1,'d',.1),(5,2,'a',.4),(5,3,'d',.1),(5,4,'a',.5),(5,4,'c',.6),(6,1,'b',.3),(6,2,'b',.4),(6,3,'a',.1),(6,4,'a',.1),(6,4,'b',.2)) t(seq_id,pos,item,p)"""
TOY_W = "SELECT * FROM (VALUES ('a',.8),('b',1.0),('c',.9),('d',.9),('e',.7),('f',.9),('g',.8)) t(item,weight)"


def head(work: str, weighted: bool = True, certain: bool = False, where: str = "TRUE") -> str:
    """CTEs occ0 (seq_id, pos, item, p), w (item, weight) and occ (with weight)."""
    if work == "toy":
        occ, w = f"SELECT seq_id::BIGINT AS seq_id, pos, item, p::DOUBLE AS p FROM ({TOY})", f"SELECT item, weight::DOUBLE AS weight FROM ({TOY_W})"
    elif work == "vector_bins":
        occ, w = VECTORS, f"SELECT item, {clipped(chr(39) + 'w|' + chr(39) + ' || item', 0.125)} AS weight FROM (SELECT DISTINCT item FROM occ0)"
    else:
        p = "1.0::DOUBLE" if certain else clipped("'p|' || seq_id::VARCHAR || '|' || pos::VARCHAR || '|' || item", 0.25)
        occ = f"SELECT seq_id::BIGINT AS seq_id, pos::BIGINT AS pos, item, {p} AS p FROM ({BASE[work]})"
        w = f"SELECT item, {clipped(chr(39) + 'w|' + chr(39) + ' || item', 0.125)} AS weight FROM (SELECT DISTINCT item FROM occ0)"
    if not weighted:
        w = "SELECT DISTINCT item, 1.0::DOUBLE AS weight FROM occ0"
    return f"WITH occ0 AS MATERIALIZED ({occ}), w AS MATERIALIZED ({w}), occ AS MATERIALIZED (SELECT o.*, weight FROM occ0 o JOIN w USING (item) WHERE {where})"


VECTORS = """SELECT seq_id, pos, 'c' || (i - 1)::VARCHAR AS item, round(v / sum(v) OVER (PARTITION BY seq_id, pos), 4) AS p FROM (
  SELECT seq_id, pos, i, round(exp(x::DOUBLE * 4), 4) AS v, row_number() OVER (PARTITION BY seq_id, pos ORDER BY round(exp(x::DOUBLE * 4), 4) DESC, i) AS k FROM (
    SELECT label::BIGINT AS seq_id, vec_id AS pos, unnest(embedding) AS x, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL)) WHERE k <= 3"""


def thresholds(min_sup: float, wgt_fct: float = 1.0, value: str | None = None) -> str:
    t = value or f"{min_sup} * (SELECT count(DISTINCT seq_id) FROM occ) * (SELECT sum(weight) / count(*) FROM occ) * {wgt_fct}"
    return f"thr AS MATERIALIZED (SELECT {t} AS t, (SELECT max(weight) FROM occ) AS mw)"


def levels(depth: int, prune: bool = True) -> str:
    """CTEs l1..ld (ends by position), e1..ed (supports), k1..kd (what may grow)."""
    out, live = [], "SELECT * FROM occ"
    for d in range(1, depth + 1):
        if d == 1:
            body = "SELECT seq_id, pos, '(' || item || ')' AS pat, item AS last, p AS pr, weight AS sw FROM occ"
        else:
            prev = f"(SELECT * FROM l{d - 1} WHERE pat IN (SELECT pat FROM k{d - 1}))"
            body = f"""SELECT seq_id, pos, pat, last, max(pr) AS pr, any_value(sw) AS sw FROM (
              SELECT o.seq_id, o.pos, m.pat || '(' || o.item || ')' AS pat, o.item AS last, m.pr * o.p AS pr, m.sw + o.weight AS sw FROM {prev} m JOIN live o ON o.seq_id = m.seq_id AND o.pos > m.pos
              UNION ALL SELECT o.seq_id, o.pos, left(m.pat, length(m.pat) - 1) || ' ' || o.item || ')', o.item, m.pr * o.p, m.sw + o.weight FROM {prev} m JOIN live o ON o.seq_id = m.seq_id AND o.pos = m.pos AND o.item > m.last
            ) GROUP BY seq_id, pos, pat, last"""
        out.append(f"l{d} AS MATERIALIZED ({body})")
        out.append(f"e{d} AS MATERIALIZED (SELECT pat, sum(best) AS es, count(*) AS support, any_value(sw) / {d} AS seq_weight, {d} AS length FROM (SELECT pat, seq_id, max(pr) AS best, any_value(sw) AS sw FROM l{d} GROUP BY pat, seq_id) GROUP BY pat)")
        keep = "es * (SELECT mw FROM thr) >= (SELECT t FROM thr) * (1 - 1e-9)" if prune else "TRUE"
        out.append(f"k{d} AS MATERIALIZED (SELECT pat FROM e{d} WHERE {keep})")
        if d == 1:
            live = "SELECT * FROM occ WHERE '(' || item || ')' IN (SELECT pat FROM k1)"
            out.append(f"live AS MATERIALIZED ({live})")
    return ", ".join(out)


def all_levels(depth: int) -> str:
    return " UNION ALL ".join(f"SELECT * FROM e{d}" for d in range(1, depth + 1))


RESULT = f"""SELECT '<' || pat || '>' AS pattern, length::BIGINT AS length, (length(pat) - length(replace(pat, '(', '')))::BIGINT AS n_events, support::BIGINT AS support,
  {r6('es')} AS es, {r6('seq_weight')} AS seq_weight, {r6('es * seq_weight')} AS wes"""


def mined(work: str, min_sup: float, depth: int, weighted: bool = True, certain: bool = False, value: str | None = None, wgt_fct: float = 1.0) -> str:
    """CTEs up to `found` (pat, es, support, seq_weight, length): the frequent patterns."""
    return f"""{head(work, weighted, certain)}, {thresholds(min_sup, wgt_fct, value)}, {levels(depth)},
      found AS MATERIALIZED (SELECT * FROM ({all_levels(depth)}) WHERE es * seq_weight >= (SELECT t FROM thr) * (1 - 1e-9))"""


def mine(work: str, min_sup: float, depth: int, **kw) -> str:
    return f"{mined(work, min_sup, depth, **kw)} {RESULT} FROM found"


def candidates(work: str, runs: list[tuple[float, str, str]], depth: int, weighted: bool) -> str:
    """CTEs c<run>_<level> (pat, mp, mw): what each run (min_sup, support cap, weight cap) takes for a candidate, and thr.

    For workloads with one item an event. Caps are computed by their definition, level by level: the best probability of an
    item after a prefix's earliest end, and as weight cap the heaviest item that keeps itself alive.
    """
    out = [head(work, weighted), "n AS MATERIALIZED (SELECT count(DISTINCT seq_id) * sum(weight) / count(*) AS n, max(weight) AS gw FROM occ)"]
    for r, (sup, cap, weight) in enumerate(runs):
        least = f"{sup} * n * (1 - 1e-9)"
        for d in range(1, depth + 1):
            if d == 1:
                best = "SELECT '' AS pat, 1.0 AS mp, 0.0 AS mw, seq_id, item, any_value(weight) AS weight, max(p) AS b FROM occ GROUP BY seq_id, item"
            else:
                best = f"SELECT f.pat, f.mp, f.mw, f.seq_id, o.item, any_value(o.weight) AS weight, max(o.p) AS b FROM f{r}_{d - 1} f JOIN occ o ON o.seq_id = f.seq_id AND o.pos > f.e0 GROUP BY f.pat, f.mp, f.mw, f.seq_id, o.item"
            value = "any_value(mp) * sum(b)" if cap == "tight" else "any_value(mp) * max(b) * count(*)"
            top = "gw" if weight == "global" else f"greatest(mw, coalesce(max(weight) FILTER (cap * greatest(mw, weight) >= {least}) OVER (PARTITION BY pat), 0))"
            caps = f"SELECT pat, item, any_value(mw) AS mw, any_value(weight) AS weight, any_value(mp) * max(b) AS mp, {value} AS cap FROM ({best}) GROUP BY pat, item"
            out.append(f"c{r}_{d} AS MATERIALIZED (SELECT pat || '(' || item || ')' AS pat, mp, greatest(mw, weight) AS mw FROM (SELECT *, {top} AS top FROM ({caps}), n), n WHERE cap * top >= {sup} * n.n * (1 - 1e-9))")
            if d < depth:
                if d == 1:
                    ends = f"SELECT o.seq_id, c.pat, any_value(c.mp) AS mp, any_value(c.mw) AS mw, min(o.pos) AS e0 FROM occ o JOIN c{r}_1 c ON c.pat = '(' || o.item || ')' GROUP BY o.seq_id, c.pat"
                else:
                    ends = f"SELECT o.seq_id, c.pat, any_value(c.mp) AS mp, any_value(c.mw) AS mw, min(o.pos) AS e0 FROM f{r}_{d - 1} f JOIN occ o ON o.seq_id = f.seq_id AND o.pos > f.e0 JOIN c{r}_{d} c ON c.pat = f.pat || '(' || o.item || ')' GROUP BY o.seq_id, c.pat"
                out.append(f"f{r}_{d} AS MATERIALIZED ({ends})")
    low = min(sup for sup, _, _ in runs)
    out.append(f"thr AS MATERIALIZED (SELECT {low} * n AS t, gw AS mw FROM n)")
    return ", ".join(out)


def candidate_counts(work: str, runs: list[tuple[float, str, str]], depth: int, longest: int, weighted: bool) -> str:
    """One row per run: its candidates over all levels, and how many patterns are frequent."""
    rows = []
    for r, (sup, cap, weight) in enumerate(runs):
        many = " + ".join(f"(SELECT count(*) FROM c{r}_{d})" for d in range(1, depth + 1))
        rows.append(f"SELECT '{work}' AS workload, {sup}::DOUBLE AS min_sup, '{cap}' AS support_cap, '{weight}' AS weight_cap, ({many})::BIGINT AS candidates, (SELECT count(*) FROM ({all_levels(longest)}), n WHERE es * seq_weight >= {sup} * n * (1 - 1e-9))::BIGINT AS frequent")
    return f"{candidates(work, runs, depth, weighted)}, {levels(longest)} SELECT *, round((candidates - frequent)::DOUBLE / candidates, 6) AS false_ratio FROM ({' UNION ALL '.join(rows)})"
