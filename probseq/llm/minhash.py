"""MinHash near-duplicates with min-max hashing.

Each permutation of the shingle hashes keeps its minimum and its maximum, so a signature needs half the hash
evaluations. Minima are banded with minima and maxima with maxima: within a band all values come from different
permutations, and a band agrees with probability J^rows for either kind. With 40 bands of 6 a pair of similarity 0.8 is
missed with probability 5e-6.

Equal shingle sets are one node (a 64-bit hash of the set). Nodes that share a band are candidates, but pairs within a
band are not enumerated: every band compares its members with PIVOTS of them, then those still apart with MORE_PIVOTS
of the largest part that confirmed links made, and only what is left apart goes through an exact prefix join of full sets. So a group of copies costs a few comparisons a
member, a group of texts just under the similarity costs hardly any, and no candidate link between components goes
untested. A pair of the first kind is looked at only if sizes and one-bit signatures allow the similarity
(missed with a chance below 3e-7), and links are confirmed on full sets.

Laws: words are runs of bytes other than 0x20 and 0x09-0x0D, with A-Z lower-cased. A document's set has its distinct
`words`-word shingles; with fewer words the whole sequence is the one shingle; without words the set is empty and linked
with nothing. Defined results: null texts are empty; null ids come after all others; repeated rows are linked copies of
one id; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import EOS_ORDER, by_sort, discard, gather, list_array, map_parts, order_key, release, settle, utf8
from probseq.llm.components import components

BANDS, ROWS = 40, 6
COUNTERS = 18  # bits of an item that choose its counter, for the order of the prefix join
SALTS = 16  # parts of a component's nodes that meet its smallest id
STRETCH = 4 << 20  # bytes that are split into words at once
MORE_PIVOTS = 8  # members of a band's largest part that the others are compared with next
PIVOTS = 1  # members of a band that all others are compared with first
_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_inverse = pow(int(_B), -1, 1 << 64)
_lower = np.arange(256, dtype=np.uint8)
_lower[65:91] += 32
_white = np.zeros(256, bool)
_white[[0x20, *range(0x09, 0x0E)]] = True


def mix(h: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(32))) * _B
        h = (h ^ (h >> np.uint64(29))) * _A
        return h ^ (h >> np.uint64(32))


def powers(base: int, n: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        p = np.full(n, base, np.uint64)
        p[:1] = 1
        return np.multiply.accumulate(p)


def word_hashes(body: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word in order, words of each document); a long text is split at white space into stretches."""
    if not len(body):
        return np.zeros(0, np.uint64), np.zeros(len(off) - 1, np.int64)
    if len(off) == 2 and len(body) > STRETCH:
        found, at = [], 0
        while at < len(body):
            to = at + STRETCH
            while to < len(body) and not _white[body[to]]:
                ahead = np.flatnonzero(_white[body[to : to + STRETCH]])
                to += int(ahead[0]) if len(ahead) else STRETCH
            to = min(to, len(body))
            found.append(_words(body[at:to], np.array([0, to - at]))[0])
            at = to
        h = np.concatenate(found)
        return h, np.array([len(h)])
    return _words(body, off)


def _words(body: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    edge = np.zeros(len(body) + 1, bool)
    edge[off] = True
    word = ~_white[body]
    before = np.concatenate([[False], word[:-1]]) & ~edge[:-1]
    after = np.concatenate([word[1:], [False]]) & ~edge[1:]
    start, stop = np.flatnonzero(word & ~before), np.flatnonzero(word & ~after) + 1
    with np.errstate(over="ignore"):
        sums = np.zeros(len(body) + 1, np.uint64)
        np.cumsum((_lower[body].astype(np.uint64) + np.uint64(1)) * powers(int(_B), len(body)), out=sums[1:])
        back = powers(_inverse, len(body))
        h = (sums[stop] - sums[start]) * back[start]
        h = mix(h + (stop - start).astype(np.uint64) * _A)
    return h, np.diff(np.searchsorted(start, off))


def shingles(body: np.ndarray, off: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """(sorted distinct shingle hashes of every document in turn, their number for each)."""
    h, many = word_hashes(body, off)
    begin = np.cumsum(many) - many
    count = np.where(many >= words, many - words + 1, np.minimum(many, 1))
    out = np.zeros(int(count.sum()), np.uint64)
    place = np.cumsum(count) - count
    for n in range(1, words + 1):  # documents of n words, or of at least `words`
        docs = np.flatnonzero(many == n if n < words else many >= words)
        if len(docs):
            at = gather(begin[docs], count[docs])
            acc = h[at]
            with np.errstate(over="ignore"):
                for k in range(1, n):
                    acc = mix(acc) * _A + h[at + k]
                out[gather(place[docs], count[docs])] = mix(acc + np.uint64(n))
    for a, b in zip(place.tolist(), (place + count).tolist(), strict=True):
        out[a:b].sort()
    doc = np.repeat(np.arange(len(count)), count)
    new = np.ones(len(out), bool)
    new[1:] = (out[1:] != out[:-1]) | (doc[1:] != doc[:-1])
    return out[new], np.bincount(doc[new], minlength=len(count))


def set_ids(sets: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each set; 0 for empty sets."""
    out = np.zeros(len(sizes), np.uint64)
    full = np.flatnonzero(sizes)
    if len(full):
        begin = (np.cumsum(sizes) - sizes)[full]
        with np.errstate(over="ignore"):
            out[full] = mix(np.add.reduceat(mix(sets), begin) * _A + np.bitwise_xor.reduceat(mix(sets ^ _A), begin) + sizes[full].astype(np.uint64))
    return out.view(np.int64)


def band_keys(sets: np.ndarray, sizes: np.ndarray, bands: int, rows: int, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """For documents with a set: band keys, one half from minima, the other from maxima of the same permutations;
    and one bit of each value of the signature, packed into words."""
    half = (bands + 1) // 2
    rng = np.random.default_rng(seed)
    salt = rng.integers(0, 1 << 63, half * rows, dtype=np.uint64)
    odd = rng.integers(0, 1 << 63, half * rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    full = np.flatnonzero(sizes)
    begin = (np.cumsum(sizes) - sizes)[full]
    keys = np.zeros((len(full), 2 * half), np.uint64)
    bits = np.zeros((len(full), words_of(bands, rows)), np.uint64)
    if not len(full):
        return keys[:, :bands], bits
    x = np.empty_like(sets)
    with np.errstate(over="ignore"):
        for i in range(half * rows):
            np.bitwise_xor(sets, salt[i], out=x)
            np.multiply(x, odd[i], out=x)
            for part, reduce in ((0, np.minimum), (half, np.maximum)):
                k, t = part + i // rows, 2 * i + (part > 0)
                value = reduce.reduceat(x, begin)
                keys[:, k] = mix(keys[:, k] * _A + value + np.uint64(k))
                bits[:, t // 64] |= (value >> np.uint64(20) & np.uint64(1)) << np.uint64(t % 64)
    return keys[:, :bands], bits


def words_of(bands: int, rows: int) -> int:
    return -(-2 * ((bands + 1) // 2) * rows // 64)


def least_agreement(num: int, den: int, bands: int, rows: int) -> int:
    """Signature bits in which a pair of similarity num / den agrees at least, but for a chance below 3e-7.

    A bit agrees with probability (1 + J) / 2; both values of a permutation may move together, which doubles the variance.
    """
    n, p = 2 * ((bands + 1) // 2) * rows, (1 + num / den) / 2
    return int(n * p - 5 * (2 * n * p * (1 - p)) ** 0.5)


def sketch(rows: DataFrame, names: list[str], words: int, bands: int, n_rows: int) -> DataFrame:
    """names, node (64-bit hash of the set), n_shingles and band keys of rows with a binary `_body`."""

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        body, off = utf8(batch, "_body")
        sets, sizes = shingles(body, off, words)
        keys, bits = band_keys(sets, sizes, bands, n_rows)
        own = [batch.column(i) for i in range(len(names))]
        return pa.RecordBatch.from_arrays([*own, pa.array(set_ids(sets, sizes)), pa.array(sizes), list_array(keys.view(np.int64).ravel(), np.where(sizes > 0, bands, 0), pa.int64()), list_array(bits.view(np.int64).ravel(), np.where(sizes > 0, bits.shape[1], 0), pa.int64())], [*names, "node", "n_shingles", "keys", "bits"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*names).schema)
    return map_parts(rows.select(*names, "_body"), "_body", part, f"{schema}, node long, n_shingles long, keys array<long>, bits array<long>", 1 << 20)


def full_sets(rows: DataFrame, words: int) -> DataFrame:
    """(node, items): the sorted shingle hashes as bytes."""

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        body, off = utf8(batch, "_body")
        sets, sizes = shingles(body, off, words)
        stop = np.concatenate([[0], np.cumsum(sizes)])
        items = [sets[a:b].tobytes() for a, b in zip(stop[:-1].tolist(), stop[1:].tolist(), strict=True)]
        return pa.RecordBatch.from_arrays([pa.array(set_ids(sets, sizes)), pa.array(items, pa.binary())], ["node", "items"])

    return map_parts(rows.select("_body"), "_body", part, "node long, items binary", 1 << 20)


def confirmed(pairs: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """Pairs (a, b) with whether den * intersection >= num * union on their full sets."""
    j = by_sort(by_sort(pairs, sets.select(F.col("node").alias("a"), F.col("items").alias("_x")), "a"), sets.select(F.col("node").alias("b"), F.col("items").alias("_y")), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        for batch in batches:
            ok = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = np.concatenate([p, q])
                both.sort()
                common = int((both[1:] == both[:-1]).sum())
                ok.append(den * common >= num * (len(both) - common))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(ok, pa.bool_())], ["a", "b", "linked"])

    return j.select("a", "b", "_x", "_y").mapInArrow(run, "a long, b long, linked boolean")


def spread(links: DataFrame, steps: int = 3) -> DataFrame:
    """(node, root): the smallest node within `steps` links. Equal roots are connected; others may be, too."""
    both = links.select(F.col("a").alias("v"), F.col("b").alias("u")).union(links.select(F.col("b").alias("v"), F.col("a").alias("u")))
    root = both.groupBy("v").agg(F.least(F.min("u"), F.col("v")).alias("r"))
    for _ in range(steps - 1):
        beyond = by_sort(both, root.select(F.col("v").alias("u"), "r"), "u").groupBy("v").agg(F.min("r").alias("r2"))
        root = by_sort(root, beyond, "v").select("v", F.least("r", "r2").alias("r"))
    return root.select(F.col("v").alias("node"), F.col("r").alias("root"))


def _counter(items: np.ndarray) -> np.ndarray:
    return (mix(items) >> np.uint64(64 - COUNTERS)).astype(np.int64)


def item_counts(sets: DataFrame) -> np.ndarray:
    """How often the items of each counter occur in all sets: 2^COUNTERS numbers whatever the size of the input."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(1 << COUNTERS, np.int64)
        for batch in batches:
            body, _ = utf8(batch, "items")
            counts += np.bincount(_counter(np.frombuffer(body.tobytes(), np.uint64)), minlength=1 << COUNTERS)
        used = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(counts[used])], ["counter", "n"])

    sums = sets.select("items").mapInArrow(run, "counter int, n long").groupBy("counter").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(1 << COUNTERS, np.int64)
    out[sums.column("counter").to_numpy()] = sums.column("n").to_numpy()
    return out


def prefix_pairs(sets: DataFrame, num: int, den: int) -> DataFrame:
    """Distinct pairs (a, b) of nodes with different roots that may reach the similarity; none that does is left out.

    Items are put in one order, rare ones first. Sets that reach the similarity share an item among the first
    n - ceil(n num / den) + 1 of each, and from the first shared one on there is room for the overlap that they need.
    The order comes from counts over all sets; it decides how many pairs are looked at, not which are found.
    """
    common = sets.sparkSession.sparkContext.broadcast(item_counts(sets))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = common.value
        for batch in batches:
            out: list[list[np.ndarray]] = [[], [], [], [], []]
            for node, root, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                s = np.frombuffer(x.as_buffer(), np.uint64)
                first = s[np.lexsort((s, counts[_counter(s)]))][: len(s) - -(-len(s) * num // den) + 1]
                k = len(first)
                for c, v in zip(out, (first.view(np.int64), np.full(k, node), np.full(k, root), np.full(k, len(s)), np.arange(k)), strict=True):
                    c.append(v)
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in out], ["item", "node", "root", "n", "place"])

    rows = sets.select("node", "root", "items").mapInArrow(run, "item long, node long, root long, n long, place long")
    x, y = (rows.select("item", *(F.col(c).alias(p + c) for c in ["node", "root", "n", "place"])) for p in "xy")
    room = F.least(F.col("xn") - F.col("xplace"), F.col("yn") - F.col("yplace"))
    sizes = F.least("xn", "yn") * F.lit(den) >= F.greatest("xn", "yn") * F.lit(num)
    enough = room * F.lit(num + den) >= (F.col("xn") + F.col("yn")) * F.lit(num)
    met = by_sort(x, y.withColumnRenamed("item", "_i"), (F.col("item") == F.col("_i")) & (F.col("xnode") < F.col("ynode")) & (F.col("xroot") != F.col("yroot")) & sizes & enough)
    return met.select(F.col("xnode").alias("a"), F.col("ynode").alias("b")).distinct()


def link(docs: DataFrame, words: int = 5, num: int = 80, den: int = 100, bands: int = BANDS, rows: int = ROWS, id_col: str = "doc_id", text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Every row with n_shingles, component_id (smallest id reachable by links of similarity >= num / den) and kept."""
    names = keep if keep is not None else [id_col]
    body = F.coalesce(F.col(text), F.lit("")).cast("binary")
    base = docs.select(*(F.col(c).alias(f"_keep{i}") for i, c in enumerate(names)), order_key(id_col).alias("_order"), F.xxhash64(body).alias("_text_hash"), body.alias("_body"))
    sketched = settle(sketch(base, ["_order", "_text_hash"], words, bands, rows), "sketches", last=True)
    filled = sketched.where("n_shingles > 0")
    many_words, agree = words_of(bands, rows), least_agreement(num, den, bands, rows)
    sig = [f"s{k}" for k in range(many_words)]
    # copies are one node from here on; bands carry nothing but it
    ones = [F.first(c).alias(c) for c in ("n_shingles", "keys", "bits")]
    uniq = settle(filled.groupBy("node").agg(*ones, F.min("_order").alias("_first"), F.min(F.struct("_order", "_text_hash")).alias("_one")), "sets-once", last=True)
    banded = uniq.select("node", F.explode(F.transform("keys", lambda k, i: F.xxhash64(i, k))).alias("bucket"))
    masks = [_mask(k) for k in range(PIVOTS)]
    pivots = [F.min(F.col("node").bitwiseXOR(F.lit(m))).bitwiseXOR(F.lit(m)).alias(f"_p{k}") for k, m in enumerate(masks)]
    shared = banded.groupBy("bucket").agg(F.min("node").alias("_low"), F.max("node").alias("_high"), *pivots).where("_low <> _high").drop("_low", "_high")
    members = settle(by_sort(banded, shared, "bucket").select("bucket", "node", *(f"_p{k}" for k in range(PIVOTS))), "bands", last=True)
    wanted = by_sort(uniq, members.select("node").distinct(), "node", "left_semi")
    nodes = settle(wanted.select("node", F.col("n_shingles").alias("n"), *(F.get("bits", F.lit(k)).alias(c) for k, c in enumerate(sig)), "_one"), "nodes")
    # one text per node with a candidate
    texts = by_sort(base.select("_order", "_text_hash", "_body"), nodes.select("_one.*"), ["_order", "_text_hash"], "left_semi")
    sets = settle(full_sets(texts, words).dropDuplicates(["node"]), "sets", last=True)

    def likely(x: str, y: str):
        """Sizes and signature bits that a similarity of num / den allows."""
        same = sum((F.bit_count(F.col(x + c).bitwiseXOR(F.col(y + c))) for c in sig), F.lit(0))
        sizes = F.least(x + "n", y + "n") * F.lit(den) >= F.greatest(x + "n", y + "n") * F.lit(num)
        return sizes & (same <= F.lit(2 * ((bands + 1) // 2) * rows - agree))

    # every member against the pivots of its bands
    star = members.select("node", F.explode(F.array(*(F.col(f"_p{k}") for k in range(PIVOTS)))).alias("pivot")).where("node <> pivot")
    star = star.select(F.least("node", "pivot").alias("a"), F.greatest("node", "pivot").alias("b")).distinct()
    x, y = nodes.select(*(F.col(c).alias("x" + c) for c in ["node", "n", *sig])), nodes.select(*(F.col(c).alias("y" + c) for c in ["node", "n", *sig]))
    pairs = by_sort(by_sort(star, x, F.col("a") == F.col("xnode")), y, F.col("b") == F.col("ynode")).where(likely("x", "y")).select("a", "b")
    tested = settle(confirmed(pairs, sets, num, den), "pairs", last=True)
    links = tested.where("linked").select("a", "b")
    root = settle(spread(links), "roots")
    # those apart from most of a band: against several members of its largest part
    inside = by_sort(members.select("bucket", "node"), root, "node", "left").withColumn("root", F.coalesce("root", "node"))
    far = [_mask(PIVOTS + k) for k in range(MORE_PIVOTS)]
    parts = inside.groupBy("bucket", "root").agg(F.count(F.lit(1)).alias("_many"), *(F.min(F.col("node").bitwiseXOR(F.lit(m))).bitwiseXOR(F.lit(m)).alias(f"_p{k}") for k, m in enumerate(far)))
    chosen_part = F.max_by(F.struct("root", *(f"_p{k}" for k in range(MORE_PIVOTS))), F.struct("_many", "root")).alias("_top")
    top = parts.groupBy("bucket").agg(F.count(F.lit(1)).alias("_parts"), chosen_part).where("_parts > 1").select("bucket", F.col("_top.root").alias("_to"), *(F.col(f"_top._p{k}").alias(f"_p{k}") for k in range(MORE_PIVOTS)))
    asked = by_sort(inside, top, "bucket").where("root <> _to").groupBy("node", "_to").agg(*(F.min(f"_p{k}").alias(f"_p{k}") for k in range(MORE_PIVOTS)))
    near = asked.select("node", F.explode(F.array_distinct(F.array(*(F.col(f"_p{k}") for k in range(MORE_PIVOTS))))).alias("pivot"))
    near = near.select(F.least("node", "pivot").alias("a"), F.greatest("node", "pivot").alias("b")).distinct()
    near = by_sort(near, tested.select("a", "b"), ["a", "b"], "left_anti")
    x, y = nodes.select(*(F.col(c).alias("x" + c) for c in ["node", "n", *sig])), nodes.select(*(F.col(c).alias("y" + c) for c in ["node", "n", *sig]))
    second = by_sort(by_sort(near, x, F.col("a") == F.col("xnode")), y, F.col("b") == F.col("ynode")).where(likely("x", "y")).select("a", "b")
    late = settle(confirmed(second, sets, num, den), "pairs")
    both = tested.unionByName(late)
    links = both.where("linked").select("a", "b")
    coarse, root = root, settle(spread(links), "roots")
    # what shares a band but not a part: an exact prefix join of these nodes' full sets
    inside = by_sort(members.select("bucket", "node"), root, "node", "left").withColumn("root", F.coalesce("root", "node"))
    apart = inside.groupBy("bucket").agg(F.min("root").alias("_r0"), F.max("root").alias("_r1")).where("_r0 <> _r1").select("bucket")
    left = by_sort(inside, apart, "bucket", "left_semi").groupBy("node").agg(F.first("root").alias("root"))
    loose = settle(by_sort(sets, left, "node").select("node", "root", "items"), "apart", last=True)
    rest = by_sort(prefix_pairs(loose, num, den), both.select("a", "b"), ["a", "b"], "left_anti")
    more = settle(confirmed(rest, sets, num, den).where("linked").select("a", "b"), "links", last=True)
    discard(members, nodes, sets, coarse, root, loose)
    root = components(links.unionByName(more))
    discard(tested, late, more)
    # copies are one node with their smallest id; nodes of a component meet its smallest id in salted parts
    firsts = uniq.select("node", "_first")
    linked = by_sort(root, firsts, "node").withColumn("_salt", F.pmod("node", F.lit(SALTS)))
    low = linked.groupBy("root").agg(F.min("_first").alias("_least")).withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)).cast("array<bigint>")))
    known = by_sort(linked, low, ["root", "_salt"]).select("node", "_least")
    own = by_sort(firsts, known, "node", "left").select("node", F.coalesce("_least", "_first").alias("_least"))
    placed = by_sort(sketched, own, "node", "left").select("_order", "_text_hash", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("_least")).otherwise(F.col("_order")).alias("_least"))
    placed = settle(placed, "groups", last=True)
    discard(sketched, uniq, root)
    real = F.when(F.col("_least") < EOS_ORDER, F.col("_least")).alias("component_id")
    kept = (F.col("_order") == F.col("_least")).alias("kept")
    if keep is None:
        return placed.select(F.when(F.col("_order") < EOS_ORDER, F.col("_order")).alias(id_col), "n_shingles", real, kept)
    out = by_sort(base.drop("_body"), placed.distinct(), ["_order", "_text_hash"])
    return out.select(*(F.col(f"_keep{i}").alias(c) for i, c in enumerate(names)), "n_shingles", real, kept)


def _mask(step: int) -> int:
    """Another order of nodes for each round."""
    return int(mix(np.array([step + 1], np.uint64)).view(np.int64)[0])

