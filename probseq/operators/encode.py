"""Encoding of occurrences: dictionary, suffix maxima, packed sequences.

Canonical rows are (seq_id long, pos, item string, p double), unique by (seq_id, pos, item).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from probseq.operators.kernel import CELLS, Batch, batches_of, gathered

OCC = ["seq_id", "pos", "item", "p"]
PACKED = "seq_id long, events array<struct<pos:int,item:int,p:double>>"
BLOCK = 1 << 19  # occurrences of a block of sequences
BLOCKS = "names array<string>, lengths binary, pos binary, item binary, p binary"


def merge(occ: DataFrame, how: str = "max") -> DataFrame:
    """One row per (seq_id, pos, item): the largest probability, or the noisy-or of all."""
    if how not in ("max", "noisy_or"):
        raise ValueError("how must be max or noisy_or")
    p = F.max("p") if how == "max" else F.when(F.max("p") >= 1, F.lit(1.0)).otherwise(1 - F.exp(F.sum(F.log1p(-F.least("p", F.lit(1 - 1e-16))))))
    return occ.groupBy("seq_id", "pos", "item").agg(p.alias("p"))


def faults(occ: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """Rows that no method may see, with a reason."""
    reason = (
        F.when(F.col("seq_id").isNull() | F.col("pos").isNull() | F.col("item").isNull() | F.col("p").isNull(), "null")
        .when(F.isnan("p") | (F.col("p") <= 0) | (F.col("p") > 1), "probability")
        .when(F.col("item").rlike(r"[() <>]") | (F.col("item") == ""), "name")
    )
    rows = occ.select(*OCC)
    if weights is not None:
        known = weights.where(F.col("weight") > 0).select(F.col("item").alias("_known")).distinct()
        rows = rows.join(known, rows["item"] == known["_known"], "left")
        reason = reason.when(F.col("_known").isNull(), "weight")
    twice = F.count(F.lit(1)).over(Window.partitionBy("seq_id", "pos", "item")) > 1
    return rows.withColumn("reason", reason.when(twice, "repeated")).where(F.col("reason").isNotNull()).select(*OCC, "reason")


def accepted(occ: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """Rows without faults, repeats merged by their maximum."""
    good = occ.select(*OCC).where(
        F.col("seq_id").isNotNull() & F.col("pos").isNotNull() & (F.col("p") > 0) & (F.col("p") <= 1) & ~F.isnan("p") & ~F.col("item").rlike(r"[() <>]") & (F.col("item") != "")
    )
    if weights is not None:
        good = good.join(weights.where(F.col("weight") > 0).select("item").distinct(), "item", "left_semi").select(*OCC)
    return merge(good)


def dictionary(occ: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """(item, weight, occ, seqs, mx, sm): how often each item occurs, in how many sequences, and the maximum and sum
    over sequences of its best probability there (null without a column p)."""
    p = F.col("p") if "p" in occ.columns else F.lit(None).cast("double")
    per = occ.groupBy("item", "seq_id").agg(F.count(F.lit(1)).alias("n"), F.max(p).alias("best"))  # map-side combine, then one row per pair
    counts = per.groupBy("item").agg(F.sum("n").alias("occ"), F.count(F.lit(1)).alias("seqs"), F.max("best").alias("mx"), F.sum("best").alias("sm"))
    if weights is None:
        return counts.select("item", F.lit(1.0).alias("weight"), "occ", "seqs", "mx", "sm")
    return counts.join(weights.select("item", "weight"), "item", "left").select("item", F.coalesce("weight", F.lit(1.0)).alias("weight"), "occ", "seqs", "mx", "sm")


def suffix_max(occ: DataFrame) -> DataFrame:
    """Adds p_sfx: the largest probability that the item has here or later in its sequence."""
    ahead = Window.partitionBy("seq_id", "item").orderBy("pos").rowsBetween(0, Window.unboundedFollowing)
    return occ.withColumn("p_sfx", F.max("p").over(ahead))


def event_number(order: list[Column], by: str = "seq_id") -> Column:
    return F.dense_rank().over(Window.partitionBy(by).orderBy(*order))


def pack(occ: DataFrame, ids: DataFrame) -> DataFrame:
    """One row per sequence with its events, items as ids; items that `ids` (item, id) lacks are left out.

    One shuffle by sequence (none where rows lie so already); every later pass over the packed rows is narrow. The ids
    come from the driver, so they go to the tasks: a join by item would put all rows of an item into one.
    """
    known = occ.join(F.broadcast(ids), "item").select("seq_id", F.struct(F.col("pos").cast("int").alias("pos"), F.col("id").alias("item"), "p").alias("e"))
    return known.groupBy("seq_id").agg(F.array_sort(F.collect_list("e")).alias("events"))


@dataclass(frozen=True)
class Packed:
    """Kept packed sequences of all items, ids in order of their names, and what `dictionary` tells of each item."""

    rows: DataFrame  # seq_id, events; or BLOCKS
    items: list[tuple[str, int, int, float, float]]  # item, occ, seqs, mx, sm
    n_seq: int

    @property
    def names(self) -> list[str] | None:
        """Names by id, where the rows are blocks with ids of their own."""
        return [x[0] for x in self.items] if "names" in self.rows.columns else None

    def close(self) -> None:
        self.rows.unpersist()


def packed_once(occ: DataFrame) -> Packed:
    """The sequences packed for several uses; the driver holds one row per item."""
    names = sorted(r["item"] for r in occ.select("item").distinct().collect())
    ids = occ.sparkSession.createDataFrame([(x, k) for k, x in enumerate(names)], "item string, id int")
    rows = pack(occ, ids).persist(StorageLevel.MEMORY_AND_DISK)
    found = _described(rows, len(names))
    return Packed(rows, [(x, *found[0, k]) for k, x in enumerate(names)], found[0, -1][1] if found else 0)


def in_blocks(occ: DataFrame, by: list[str]) -> DataFrame:
    """(*by, names, lengths, pos, item, p): sequences by `by` (whole numbers of a sequence), some BLOCK occurrences a row as
    numpy bytes, items as numbers in the block's own sorted names. All rows of a sequence must lie in one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        t = pa.Table.from_batches(held)
        del held
        seq, pos, p = (t[c].to_numpy() for c in ("seq_id", "pos", "p"))
        coded = pc.dictionary_encode(t["item"]).combine_chunks()
        coded = coded if isinstance(coded, pa.DictionaryArray) else coded.chunk(0)
        given = coded.dictionary.to_pylist()
        names = sorted(given)
        ids = {x: k for k, x in enumerate(names)}
        item = np.array([ids[x] for x in given], np.int32)[coded.indices.to_numpy()]
        keys = [t[c].to_numpy() for c in by]
        order = np.lexsort((item, pos, seq, *keys[::-1]))
        seq, pos, item, p, keys = seq[order], pos[order].astype(np.int32), item[order], p[order], [k[order] for k in keys]
        new = np.ones(len(seq), bool)
        new[1:] = seq[1:] != seq[:-1]
        part = np.zeros(len(seq), bool)
        for k in keys:
            part[1:] |= k[1:] != k[:-1]
        new |= part
        starts = np.flatnonzero(new)
        edges = [0, *np.flatnonzero(part[starts]).tolist(), len(starts)]
        begin = np.append(starts, len(seq))
        for a, b in zip(edges, edges[1:], strict=False):
            while a < b:  # whole sequences, one at least
                to = min(b, max(a + 1, int(np.searchsorted(begin, begin[a] + BLOCK, side="right")) - 1))
                x, y = begin[a], begin[to]
                used = np.flatnonzero(np.bincount(item[x:y], minlength=len(names)))
                own = np.zeros(len(names), np.int32)
                own[used] = np.arange(len(used))
                data = (np.diff(begin[a : to + 1]).astype(np.int32), pos[x:y], own[item[x:y]], p[x:y])
                head = [pa.array([int(k[x])], pa.int32()) for k in keys]
                yield pa.RecordBatch.from_arrays([*head, pa.array([[names[k] for k in used]], pa.list_(pa.string())), *(pa.array([c.tobytes()], pa.binary()) for c in data)], [*by, "names", "lengths", "pos", "item", "p"])
                a = to

    given = occ.where("seq_id is not null and pos is not null and item is not null")
    return given.select("seq_id", "pos", "item", "p", *by).mapInArrow(run, ", ".join([*(f"{c} int" for c in by), BLOCKS]))


def batches_in(parts: Iterator[pa.RecordBatch], names: list[str] | None) -> Iterator[Batch]:
    """Kernel batches of packed rows: of events, or with `names` by id of blocks."""
    if names is None:
        for column in gathered(b.column(0) for b in parts):
            for _, batch in batches_of(column, cells=2 * CELLS):
                yield batch
        return
    ids, held, size = {x: k for k, x in enumerate(names)}, [], 0
    for b in parts:
        own, *data = (b.column(b.schema.names.index(c)) for c in ("names", "lengths", "pos", "item", "p"))
        for i in range(b.num_rows):
            lengths, pos, item, p = (np.frombuffer(c[i].as_buffer(), t) for c, t in zip(data, (np.int32, np.int32, np.int32, np.float64), strict=True))
            held.append((lengths.astype(np.int64), pos, np.array([ids.get(x, -1) for x in own[i].as_py()], np.int32)[item], p))
            size += len(pos)
            if size >= CELLS // 8:
                yield Batch(*map(np.concatenate, zip(*held, strict=True)))
                held, size = [], 0
    if held:
        yield Batch(*map(np.concatenate, zip(*held, strict=True)))


def packed_parts(blocks: DataFrame, by: str | None = None, values=(0,)) -> dict[int, Packed]:
    """Of kept blocks those of every value of column `by` (None: all, as 0); the driver holds a row per item and value.

    All have the ids of all items, so items that a part lacks have no occurrences there.
    """
    names = sorted(r["x"] for r in blocks.select(F.explode("names").alias("x")).distinct().collect())
    rows = blocks.withColumn("part", F.lit(0) if by is None else F.col(by)).where(F.col("part").isin(list(values)))
    rows = rows.select("names", "lengths", "pos", "item", "p", "part")
    found = _described(rows, len(names), names, True)
    zero = (0, 0, 0.0, 0.0)
    return {v: Packed(rows.where(F.col("part") == v).drop("part"), [(x, *found.get((v, k), zero)) for k, x in enumerate(names)], found.get((v, -1), zero)[1]) for v in values}


def _described(rows: DataFrame, size: int, names: list[str] | None = None, parts: bool = False) -> dict[tuple[int, int], tuple]:
    """(part, id) -> (occ, seqs, mx, sm) of packed rows, and under id -1 the number of sequences as seqs."""

    def counted(batches: Iterator[Batch]) -> list[np.ndarray]:
        n, seqs, many = 0, np.zeros(size, np.int64), np.zeros(size, np.int64)
        mx, sm = np.zeros(size), np.zeros(size)
        for batch in batches:
            n += batch.n
            many[: len(batch.counts)] += batch.counts
            for i in batch.items.tolist():
                state = batch.child(None, "S", i)
                mx[i] = max(mx[i], state.best.max())
                sm[i] += state.best.sum()
                seqs[i] += len(state.rows)
        hit = np.flatnonzero(seqs)
        return [np.append(hit, -1), np.append(many[hit], 0), np.append(seqs[hit], n), np.append(mx[hit], 0.0), np.append(sm[hit], 0.0)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches if parts else [None]:
            own = np.zeros(1, np.int64) if b is None else b.column(b.schema.names.index("part")).to_numpy()
            for v in np.unique(own).tolist():
                arrays = counted(batches_in(batches if b is None else iter([b.filter(pa.array(own == v))]), names))
                yield pa.RecordBatch.from_arrays([pa.array(a) for a in (np.full(len(arrays[0]), v), *arrays)], ["part", "id", "occ", "seqs", "mx", "sm"])

    found = (rows if parts else rows.select("events")).mapInArrow(run, "part long, id long, occ long, seqs long, mx double, sm double")
    total = found.groupBy("part", "id").agg(F.sum("occ").alias("occ"), F.sum("seqs").alias("seqs"), F.max("mx").alias("mx"), F.sum("sm").alias("sm"))
    return {(r["part"], r["id"]): tuple(r)[2:] for r in total.collect()}


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("seq_id", F.explode("events").alias("e")).select("seq_id", "e.pos", "e.item", "e.p")


def packed_maps(occ: DataFrame) -> DataFrame:
    """(seq_id, events array<struct<pos, items map<item, p>>>): a sequence as maps, for higher-order functions."""
    per = occ.groupBy("seq_id", "pos").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("item", "p")))).alias("items"))
    # maps cannot be ordered, so positions sort and maps follow by key
    return per.groupBy("seq_id").agg(F.map_from_entries(F.collect_list(F.struct("pos", "items"))).alias("_m")).select(
        "seq_id", F.transform(F.array_sort(F.map_keys("_m")), lambda k: F.struct(k.alias("pos"), F.element_at("_m", k).alias("items"))).alias("events")
    )
