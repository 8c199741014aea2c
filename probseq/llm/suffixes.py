"""Removal of repeated passages with a logarithmic family of suffix arrays.

Law: a byte goes if a `span`-byte string that covers it also starts in a document with a smaller id. Strings are judged
on the input, by bytes, within documents.

1. Anchors. Every window of `span` bytes picks its least-hashed k-gram; consecutive windows with the same pick form
   one anchored context of span to 2 span - k bytes. Equal windows pick equal anchors, so only contexts with the same
   anchor can share a window, and one context stands for about 18 windows. A context that an earlier document of the
   same part has byte for byte is marked there, so a passage that everyone copies leaves a part once.
2. Meeting. Anchors are dealt by hash. A shared window has an anchor and, as it is longer than two grams, the gram before
   or the gram after it, too. Contexts that no other document can match in either way share nothing and stop here; this is
   all that hashes decide.
3. Suffix arrays. All other contexts come with their bytes, dealt by anchor, in order of document. Equal contexts become
   one; of the rest, a batch gets a suffix array of its window starts (sorted to depth `span`), is merge-scanned against
   the levels of earlier batches for strings that an earlier document has, and becomes a level; two levels of like size
   merge into one, so there are logarithmically many.
4. Marks return to their documents, and what they cover is cut out.

`SuffixIndex` keeps the family from call to call: a batch of documents is judged against the levels of the batches before
it, then becomes a level itself, and levels of like size are merged geometrically. A level is a Parquet table of sorted
anchors by deal; bytes are fetched from stored texts only for anchors that meet.

Marks and wishes travel by the home of their text, one of HOMES by its id and hash: a task sends one row for each home, whatever
the number of texts and deals, so rows grow with the tasks and not with texts times deals.

Memory. Deals grow in number with the bytes of the input, and a task holds one of them at a time; of a deal that outgrows
BLOCK all the same (one anchor in a great share of all documents) the windows go on one by one, dealt by their own bytes.
Long texts are cut into stretches. Texts are dealt by id for fetching, and again for cutting. Defined results: null texts are empty; texts
shorter than the span keep everything; null ids come after all others; rows with the same id do not erase each other;
identical rows have identical results; an empty table gives no rows; other columns, whatever their names, are left alone.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from probseq.llm.common import discard, gather, map_parts, order_key, partitions, release, settle, slices, utf8

SPAN = 50
GRAM = 16
DEAL = 8 << 20  # bytes of text for each deal of anchors
BLOCK = 4 << 20  # contexts of one deal that are held at once
BATCH = 8192  # contexts that get a suffix array together
CHUNK = 1 << 17  # contexts whose bytes are fetched together
_P = np.uint64(0xD6E8FEB86659FD93)
_Q = np.uint64(0x9E3779B97F4A7C15)
LOW = np.uint64(0xFFFFFF)

# An anchored context: where its windows start (first, last), its anchor, and bits of the grams beside it (0: none).
NEW, KNOWN, OLD = 0, 1, 2  # to be judged; judged within its part; of an earlier batch
ENTRY = np.dtype([("anchor", "<u8"), ("order", "<i8"), ("text", "<i8"), ("first", "<u4"), ("wide", "u1"), ("state", "u1"), ("left", "<u2"), ("right", "<u2")])
# What to cut out of a text: windows first..first + wide.
SPOT = np.dtype([("first", "<u4"), ("wide", "u1")])
# A mark or a wish for bytes: such windows of a text, the deal of its anchor (-1: windows go on by their own bytes) and which part of it.
TOLD = np.dtype([("order", "<i8"), ("text", "<i8"), ("deal", "<i4"), ("first", "<u4"), ("wide", "u1"), ("sub", "u1")])
HEAD = np.dtype([("order", "<i8"), ("text", "<i8"), ("first", "<u4"), ("wide", "u1"), ("sub", "u1")])
HOMES = 4096  # a home of texts, with all their marks or wishes, must fit a task
HELD = 1 << 20  # marks and wishes that a task gathers before it sends them on
_told_schema = "mark boolean, home int, told binary"


def gram_hashes(body: np.ndarray, k: int) -> np.ndarray:
    """A mixed 64-bit hash of every k consecutive bytes; k a power of two."""
    h, p, n = (body.astype(np.uint64) + np.uint64(1)) * _Q, _P, 1
    with np.errstate(over="ignore"):
        while n < k:
            h = h[:-n] * p + h[n:] if len(h) > n else h[:0]
            p, n = p * p, 2 * n
        h ^= h >> np.uint64(32)
        h *= _P
        h ^= h >> np.uint64(29)
    return h


def beside(body: np.ndarray, start: np.ndarray, low: np.ndarray, high: np.ndarray, k: int) -> np.ndarray:
    """16 bits, never 0, of the k bytes from each start; 0 where they leave low..high."""
    inside = (start >= low) & (start + k <= high)
    at = np.where(inside, start, 0)
    h = np.zeros(len(start), np.uint64)
    with np.errstate(over="ignore"):
        for j in range(k):
            h = (h ^ body[np.minimum(at + j, len(body) - 1)]) * _P
            h ^= h >> np.uint64(31)
    return np.where(inside, np.maximum(h >> np.uint64(48), np.uint64(1)), np.uint64(0)).astype(np.uint16)


def least_in(x: np.ndarray, w: int) -> np.ndarray:
    """The minimum of every w consecutive values."""
    n = 1
    while 2 * n <= w:
        x, n = np.minimum(x[:-n], x[n:]), 2 * n
    return np.minimum(x[: len(x) - (w - n)], x[w - n :]) if n < w else x


STRETCH = 4 << 20  # bytes whose grams are held at once; places within fit LOW


def contexts(body: np.ndarray, off: np.ndarray, span: int = SPAN, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """(document, first window, windows - 1, place of the anchor, anchor hash, context hash) of every context.

    Places count from the start of `body`; at most STRETCH bytes at once.
    """
    none = tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.int64, np.uint64, np.uint64))
    if len(body) < span:
        return none
    if len(body) > STRETCH:  # long texts: overlapping stretches, cut between windows of the same document
        return _long_contexts(body, off, span, gram)
    h = gram_hashes(body, gram)
    width = span - gram + 1
    pick = (least_in((h & ~LOW) | np.arange(len(h), dtype=np.uint64), width) & LOW).astype(np.int64)
    length = np.diff(off)
    starts = np.maximum(length - span + 1, 0)
    doc = np.repeat(np.arange(len(length)), starts)
    s = gather(off[:-1], starts)
    if not len(s):
        return none
    a = pick[s]
    cut = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (doc[1:] != doc[:-1])]))
    first, last = s[cut], s[np.append(cut[1:], len(s)) - 1]
    a, doc = a[cut], doc[cut]
    # the context's own hash, which groups what is then compared byte by byte
    with np.errstate(over="ignore"):
        own = block_hash(body, first, last + span) * _Q ^ ((a - first).astype(np.uint64) << np.uint64(8)) ^ (last - first).astype(np.uint64)
    return doc, first, last - first, a, h[a], own


def block_hash(body: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
    """A hash of body[start:stop] for stops at least 32 and at most 96 bytes on: four overlapping 32-byte hashes and the length."""
    g = gram_hashes(body, 32)
    n = stop - start
    out = n.astype(np.uint64) * _P
    with np.errstate(over="ignore"):
        for at in (start, start + (n - 32) // 3, start + 2 * (n - 32) // 3, stop - 32):
            out = (out ^ (out >> np.uint64(31))) * _Q + g[at]
        out ^= out >> np.uint64(33)
        return out * _P


def _long_contexts(body: np.ndarray, off: np.ndarray, span: int, gram: int) -> tuple[np.ndarray, ...]:
    found = []
    step = STRETCH - span
    for d in range(len(off) - 1):
        for at in range(int(off[d]), max(int(off[d]) + 1, int(off[d + 1]) - span + 1), step):
            part = body[at : min(at + step + span - 1, int(off[d + 1]))]
            doc, first, wide, anchor, *rest = contexts(part, np.array([0, len(part)]), span, gram)
            found.append((doc + d, first + at, wide, anchor + at, *rest))
    return tuple(np.concatenate(c) for c in zip(*found, strict=True))


def firsts(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order that sorts by keys, last key first; whether each sorted row begins a new value of all keys but the first)."""
    order = np.lexsort(keys)
    new = np.zeros(len(order), bool)
    new[:1] = True
    for k in keys[1:]:
        s = k[order]
        new[1:] |= s[1:] != s[:-1]
    return order, new


def strings(buffer: np.ndarray, starts: np.ndarray, span: int) -> np.ndarray:
    """Fixed-width byte strings buffer[start : start + span]; equal exactly if their bytes are."""
    if not len(starts):
        return np.zeros(0, f"S{span}")
    return np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(buffer, span)[starts]).view(f"S{span}").ravel()


class SuffixFamily:
    """Suffix arrays to depth `span` of batches of contexts, as levels of geometrically falling size.

    A level is a sorted array of distinct strings and the earliest document of each. Batches come in document order.
    """

    def __init__(self, span: int = SPAN):
        self.span, self.levels = span, []

    @staticmethod
    def merge(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """One level from two; the stable sort of two sorted runs is a single merge."""
        keys, docs = np.concatenate([a[0], b[0]]), np.concatenate([a[1], b[1]])
        order = np.argsort(keys, kind="stable")
        keys, docs = keys[order], docs[order]
        new = np.concatenate([[True], keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, bool)
        at = np.flatnonzero(new)
        return keys[at], np.minimum.reduceat(docs, at) if len(at) else docs

    def scan(self, keys: np.ndarray) -> np.ndarray:
        """For sorted distinct strings, the earliest document of each in all levels."""
        best = np.full(len(keys), np.iinfo(np.int64).max)
        for level, docs in self.levels:
            joined = np.concatenate([level, keys])
            order = np.argsort(joined, kind="stable")  # level first among equals
            s = joined[order]
            same = np.flatnonzero(s[1:] == s[:-1])
            hit = order[same + 1] - len(level)
            best[hit] = np.minimum(best[hit], docs[order[same]])
        return best

    def add(self, buffer: np.ndarray, starts: np.ndarray, docs: np.ndarray) -> np.ndarray:
        """Whether each string of the batch starts in an earlier document; the batch becomes part of the family."""
        keys = strings(buffer, starts, self.span)
        array = np.argsort(keys, kind="stable")  # the batch's suffix array
        s, d = keys[array], docs[array]
        new = np.concatenate([[True], s[1:] != s[:-1]]) if len(s) else np.zeros(0, bool)
        at = np.flatnonzero(new)
        if not len(at):
            return np.zeros(0, bool)
        least = np.minimum.reduceat(d, at)
        distinct = s[at]
        earliest = np.minimum(least, self.scan(distinct))
        seen = np.empty(len(s), bool)
        seen[array] = earliest[np.cumsum(new) - 1] < d
        self.levels.append((distinct, least))
        while len(self.levels) > 1 and len(self.levels[-2][0]) < 2 * len(self.levels[-1][0]):
            b, a = self.levels.pop(), self.levels.pop()
            self.levels.append(self.merge(a, b))
        return seen


def _deal(anchor: np.ndarray, deals: int) -> np.ndarray:
    return ((anchor >> np.uint64(20)) % np.uint64(deals)).astype(np.int64)


def _sub(anchor: np.ndarray) -> np.ndarray:
    """One of 256 parts of a deal, from bits that deal nothing out."""
    return ((anchor * _Q) >> np.uint64(56)).astype(np.uint8)


def dealt_out(rows: DataFrame, deals: int) -> DataFrame:
    """Rows by deal, a few deals in each partition."""
    return rows.repartition(max(partitions(rows.sparkSession), deals // 4), "deal").sortWithinPartitions("deal")


def deals_of(rows: DataFrame, column: str = "_body") -> int:
    """How many deals the bytes of a column need."""
    size = rows.agg(F.sum(F.octet_length(column).cast("long"))).first()[0] or 0
    return max(partitions(rows.sparkSession), -(-size // DEAL))


def _by_deal(deal: np.ndarray, rows: np.ndarray) -> tuple[list[int], list[bytes]]:
    if not len(rows):
        return [], []
    order = np.argsort(deal, kind="stable")
    rows, used, begin = rows[order], *np.unique(deal[order], return_index=True)
    ends = np.append(begin[1:], len(rows))
    return used.tolist(), [rows[a:b].tobytes() for a, b in zip(begin.tolist(), ends.tolist(), strict=True)]


def _blocks(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[tuple[int, list, bool]]:
    """(deal, (old, blob) of about `most` bytes, whether the deal ends here) of rows sorted by deal."""
    now, held, size = None, [], 0
    for b in batches:
        # blobs are views of the batch, never copies
        for k, blob, old in zip(b.column(0).to_pylist(), (x.as_buffer() for x in b.column(1)), b.column(2).to_pylist() if b.num_columns > 2 else [False] * b.num_rows, strict=True):
            if held and (k != now or size > most):
                yield now, held, k != now
                held, size = [], 0
            now = k
            held.append((old, blob))
            size += blob.size
    if held:
        yield now, held, True


def home_of(order, text):
    """The home of a text; the same on arrays and on columns."""
    column = isinstance(order, Column)
    x = order.bitwiseXOR(text) if column else order ^ text
    for k in (36, 24, 12):
        x = x.bitwiseXOR(F.shiftright(x, k)) if column else x ^ (x >> k)
    return x.bitwiseAND(HOMES - 1).cast("int") if column else x & (HOMES - 1)


def told_of(found: np.ndarray, deal: int) -> np.ndarray:
    """TOLD rows of ENTRY or HEAD rows, of one deal."""
    out = np.empty(len(found), TOLD)
    for c in ("order", "text", "first", "wide"):
        out[c] = found[c]
    out["deal"], out["sub"] = deal, found["sub"] if "sub" in found.dtype.names else _sub(found["anchor"])
    return out


class Teller:
    """Gathers marks and wishes of a task, and sends them on by home."""

    def __init__(self):
        self.held, self.size = {True: [], False: []}, 0

    def add(self, rows: np.ndarray, mark: bool) -> Iterator[pa.RecordBatch]:
        self.held[mark].append(rows)
        self.size += len(rows)
        if self.size >= HELD:
            yield from self.flush()

    def flush(self) -> Iterator[pa.RecordBatch]:
        for mark, parts in self.held.items():
            rows = np.concatenate(parts) if parts else np.zeros(0, TOLD)
            self.held[mark] = []
            if not len(rows):
                continue
            home = home_of(rows["order"], rows["text"])
            by = np.lexsort((rows["text"], rows["order"], home))
            home, new = home[by], np.ones(len(by), bool)
            new[1:] = home[1:] != home[:-1]
            begin = np.flatnonzero(new)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(begin), mark)), pa.array(home[begin].astype(np.int32)), binaries(rows[by], begin)], ["mark", "home", "told"])
        self.size = 0


def binaries(rows: np.ndarray, begin: np.ndarray) -> pa.BinaryArray:
    """One value for each run of rows that begins at `begin`."""
    off = np.append(begin, len(rows)) * rows.dtype.itemsize
    return pa.BinaryArray.from_buffers(pa.binary(), len(begin), [None, pa.py_buffer(off.astype(np.int32).tobytes()), pa.py_buffer(rows.tobytes())])


def by_home(rows: DataFrame, deals: int, key: str) -> DataFrame:
    return rows.repartition(max(partitions(rows.sparkSession), deals // 4), "home").sortWithinPartitions(key)


def by_text(told: DataFrame, deals: int) -> DataFrame:
    """(_order, _text_hash, spots): one row for each text that has marks."""

    def packed(rows: np.ndarray) -> pa.RecordBatch:
        rows = rows[np.lexsort((rows["text"], rows["order"]))]
        new = np.ones(len(rows), bool)
        new[1:] = (rows["order"][1:] != rows["order"][:-1]) | (rows["text"][1:] != rows["text"][:-1])
        begin, spots = np.flatnonzero(new), np.empty(len(rows), SPOT)
        spots["first"], spots["wide"] = rows["first"], rows["wide"]
        return pa.RecordBatch.from_arrays([pa.array(rows["order"][begin]), pa.array(rows["text"][begin]), binaries(spots, begin)], ["_order", "_text_hash", "spots"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        held, now = [], None
        for b in batches:
            if not b.num_rows:
                continue
            home, rows = b.column(0).to_numpy(), utf8(b, "told")[0].view(TOLD)
            if home[-1] == now:  # one home still
                held.append(rows.copy())
                continue
            rows, now = np.concatenate([*held, rows]), home[-1]
            last = home_of(rows["order"], rows["text"]) == now
            if not last.all():
                yield packed(rows[~last])
            held = [rows[last]]
        if held:
            yield packed(np.concatenate(held))

    return by_home(told.select("home", "told"), deals, "home").mapInArrow(run, "_order long, _text_hash long, spots binary")


def repeats(body: np.ndarray, first: np.ndarray, wide: np.ndarray, span: int, order: np.ndarray, context: np.ndarray, anchor: np.ndarray) -> np.ndarray:
    """Whether an earlier document of the same part has each context, byte for byte."""
    out = np.zeros(len(first), bool)
    by, new = firsts(order, context, anchor)
    if not len(by):
        return out
    least = by[np.flatnonzero(new)][np.cumsum(new) - 1]
    may = (order[by] > order[least]) & (wide[by] == wide[least])
    rows, least = by[may], least[may]
    for k in range(0, len(rows), CHUNK):
        x, y = rows[k : k + CHUNK], least[k : k + CHUNK]
        n = wide[x] + span
        same = body[gather(first[x], n)] == body[gather(first[y], n)]
        out[x] = np.logical_and.reduceat(same, np.cumsum(n) - n)
    return out


def anchored(docs: DataFrame, deals: int, span: int, gram: int) -> DataFrame:
    """(deal, blob of ENTRY): contexts of all texts; repeats of a context within a part are known at once."""

    def part(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        body, off = utf8(batch, "_body")
        order, text = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        doc, first, wide, place, anchor, context = contexts(body, off, span, gram)
        rows = np.zeros(len(doc), ENTRY)
        rows["anchor"], rows["order"], rows["text"] = anchor, order[doc], text[doc]
        rows["first"], rows["wide"] = first - off[doc], wide
        if len(doc):
            rows["left"] = beside(body, place - gram, off[doc], off[doc + 1], gram)
            rows["right"] = beside(body, place + gram, off[doc], off[doc + 1], gram)
        known = repeats(body, first, wide, span, rows["order"], context, anchor)
        rows["state"][known] = KNOWN
        # known ones need no meeting: they are spread by text, so that no deal gets a whole group of copies
        deal = np.where(known, _deal(rows["text"].view(np.uint64) * _Q, deals), _deal(anchor, deals))
        used, blobs = _by_deal(deal, rows)
        return pa.RecordBatch.from_arrays([pa.array(used, pa.int32()), pa.array(blobs, pa.binary())], ["deal", "blob"])

    return map_parts(docs.select("_order", "_text_hash", "_body"), "_body", part, "deal int, blob binary", 2 << 20)


def shared_with(rows: np.ndarray, side: str) -> np.ndarray:
    """Whether another document has the anchor and the same gram on one side, and one of them is new."""
    out = np.zeros(len(rows), bool)
    by = np.lexsort((rows[side], rows["anchor"]))
    by = by[rows[side][by] > 0]
    if len(by):
        a, b = rows["anchor"][by], rows[side][by]
        begin = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])]))
        order = rows["order"][by]
        several = np.minimum.reduceat(order, begin) != np.maximum.reduceat(order, begin)
        several &= np.minimum.reduceat(rows["state"][by], begin) == NEW
        out[by] = np.repeat(several, np.diff(np.append(begin, len(by))))
    return out


def met(dealt: DataFrame, block: int = BLOCK) -> DataFrame:
    """Marks (mark = true) of contexts that are known, and wishes for bytes of all that another document may match.

    `dealt` has (deal, blob, old), sorted by deal. Anchors of old documents alone wish for nothing.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        alone, shared, whole = np.zeros(0, ENTRY), np.zeros(0, np.uint64), True
        teller = Teller()
        for deal, blobs, done in _blocks(batches, block * ENTRY.itemsize):
            whole = whole and done  # of a deal in several blocks, all windows go on one by one
            rows = np.concatenate([np.frombuffer(blob, ENTRY) for _, blob in blobs])
            old = np.repeat([o for o, _ in blobs], [blob.size // ENTRY.itemsize for _, blob in blobs])
            del blobs
            known = rows[(rows["state"] == KNOWN) & ~old]
            rows["state"][old] = OLD
            rows = np.concatenate([alone, rows[rows["state"] != KNOWN]])
            wish = shared_with(rows, "left") | shared_with(rows, "right")
            if len(shared):
                wish |= np.isin(rows["anchor"], shared)
            for chosen, mark in ((known, True), (rows[wish], False)):
                if len(chosen):
                    yield from teller.add(told_of(chosen, deal if whole else -1), mark)
            if done:
                alone, shared, whole = alone[:0], shared[:0], True
            else:
                alone, shared = rows[~wish], np.union1d(shared, rows["anchor"][wish])
        yield from teller.flush()

    return dealt.mapInArrow(run, _told_schema)


def asked(texts: DataFrame, wishes: DataFrame, deals: int) -> DataFrame:
    """(place, _order, _text_hash, _body, told): texts by home, after the wishes of their home; an odd place is a text's."""
    home = home_of(F.col("_order"), F.col("_text_hash"))
    own = texts.select(home.alias("home"), (home * 2 + 1).alias("place"), "_order", "_text_hash", "_body", F.lit(None).cast("binary").alias("told"))
    zero = F.lit(0).cast("long")
    told = wishes.select("home", (F.col("home") * 2).alias("place"), zero.alias("_order"), zero.alias("_text_hash"), F.lit(None).cast("binary").alias("_body"), "told")
    return by_home(told.unionByName(own), deals, "place")


def fetched(rows: DataFrame, deals: int, span: int) -> DataFrame:
    """(deal, blob): the bytes of wished contexts with their documents. A blob is a count, HEADs, then bytes."""

    def made(body: np.ndarray, start: np.ndarray, heads: np.ndarray, deal: np.ndarray) -> pa.RecordBatch:
        by = np.argsort(deal, kind="stable")
        used, begin = np.unique(deal[by], return_index=True)
        ends = np.append(begin[1:], len(by))
        blobs = []
        for a, b in zip(begin.tolist(), ends.tolist(), strict=True):
            mine = by[a:b]
            blobs.append(len(mine).to_bytes(8, "little") + heads[mine].tobytes() + body[gather(start[mine], heads["wide"][mine].astype(np.int64) + span)].tobytes())
        return pa.RecordBatch.from_arrays([pa.array(used, pa.int32()), pa.array(blobs, pa.binary())], ["deal", "blob"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        pool, known, begin = np.zeros(0, TOLD), {}, np.zeros(1, np.int64)
        for whole in batches:
            for batch in slices(whole, "_body", 2 << 20):
                place = batch.column(0).to_numpy()
                told = utf8(batch, "told")[0].view(TOLD)
                if len(told):  # of the wishes so far, only those of the first row's home are still needed
                    pool = pool[home_of(pool["order"], pool["text"]) == place[0] >> 1]
                    pool = np.concatenate([pool, told])
                    pool = pool[np.lexsort((pool["text"], pool["order"]))]
                    new = np.ones(len(pool), bool)
                    new[1:] = (pool["order"][1:] != pool["order"][:-1]) | (pool["text"][1:] != pool["text"][:-1])
                    begin = np.append(np.flatnonzero(new), len(pool))
                    known = {x: k for k, x in enumerate(zip(pool["order"][new].tolist(), pool["text"][new].tolist(), strict=True))}
                body, off = utf8(batch, "_body")
                order, text = batch.column(1).to_numpy(), batch.column(2).to_numpy()
                is_text = np.flatnonzero(place & 1)
                found = np.array([known.get(x, -1) for x in zip(order[is_text].tolist(), text[is_text].tolist(), strict=True)], np.int64)
                row, found = is_text[found >= 0], found[found >= 0]
                sizes = begin[found + 1] - begin[found]
                spots, doc = pool[gather(begin[found], sizes)], np.repeat(row, sizes)
                deal = spots["deal"].astype(np.int64)
                for k in range(0, len(spots), CHUNK):
                    own, at, to = spots[k : k + CHUNK], doc[k : k + CHUNK], deal[k : k + CHUNK]
                    alone = to < 0
                    many = np.where(alone, own["wide"].astype(np.int64) + 1, 1)
                    heads = np.zeros(int(many.sum()), HEAD)
                    row = np.repeat(np.arange(len(own)), many)
                    heads["order"], heads["text"] = order[at[row]], text[at[row]]
                    heads["first"] = own["first"][row] + gather(np.zeros(len(own), np.int64), many)
                    heads["wide"], heads["sub"] = np.where(alone[row], 0, own["wide"][row]), own["sub"][row]
                    start, to = off[at[row]] + heads["first"], to[row]
                    one = np.flatnonzero(alone[row])
                    if len(one):
                        h = block_hash_of(body, start[one], span)
                        to[one], heads["sub"][one] = _deal(h, deals), _sub(h)
                    yield made(body, start, heads, to)

    return rows.select("place", "_order", "_text_hash", "_body", "told").mapInArrow(run, "deal int, blob binary")


def block_hash_of(body: np.ndarray, start: np.ndarray, span: int) -> np.ndarray:
    """A hash of the `span` bytes from each start."""
    out = np.full(len(start), span, np.uint64)
    with np.errstate(over="ignore"):
        for k in range(span):
            out = (out ^ body[start + k]) * _P
            out ^= out >> np.uint64(29)
    return out * _Q


def whole_contexts(body: np.ndarray, start: np.ndarray, wide: np.ndarray, span: int) -> np.ndarray:
    """Each context as one fixed-width string; its first byte holds the length, so that equal strings are equal contexts."""
    most = int(wide.max()) + span + 1
    out = np.zeros((len(start), most), np.uint8)
    out[:, 0] = wide + 1
    n = wide + span
    flat = gather(np.arange(len(start)) * most + 1, n)
    out.ravel()[flat] = body[gather(start, n)]
    return out.view(f"S{most}").ravel()


def judged(body: np.ndarray, start: np.ndarray, head: np.ndarray, span: int, batch: int = BATCH) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rows of `head`, first seen window, last seen window): runs of windows that a smaller document has, too."""
    wide = head["wide"].astype(np.int64)
    by = np.argsort(head["order"], kind="stable")
    text = whole_contexts(body, start[by], wide[by], span)
    own = np.argsort(text, kind="stable")
    s, by = text[own], by[own]
    new = np.ones(len(s), bool)
    new[1:] = s[1:] != s[:-1]
    lead = by[np.flatnonzero(new)]  # the earliest of equal contexts
    group = np.cumsum(new) - 1
    del text, s
    late = by[head["order"][by] > head["order"][lead][group]]
    yield late, np.zeros(len(late), np.int64), wide[late]
    # rows as early as the first of their group share what is found for it
    level = np.flatnonzero(head["order"][by] == head["order"][lead][group])
    mates, of = by[level], group[level]
    begin = np.searchsorted(of, np.arange(len(lead) + 1))
    order = np.argsort(head["order"][lead], kind="stable")
    family = SuffixFamily(span)
    for k in range(0, len(order), batch):
        g = order[k : k + batch]
        windows = wide[lead[g]] + 1
        at = gather(start[lead[g]], windows)
        row = np.repeat(g, windows)
        seen = family.add(body, at, head["order"][lead[row]])
        hit = np.flatnonzero(seen)
        if not len(hit):
            continue
        place = at - start[lead[row]]
        fresh = np.concatenate([[True], (hit[1:] != hit[:-1] + 1) | (row[hit[1:]] != row[hit[:-1]])])
        a = hit[fresh]
        b = hit[np.append(np.flatnonzero(fresh)[1:], len(hit)) - 1]
        many = begin[row[a] + 1] - begin[row[a]]
        run = np.repeat(np.arange(len(a)), many)
        yield mates[gather(begin[row[a]], many)], place[a][run], place[b][run]


def scanned(dealt: DataFrame, span: int) -> DataFrame:
    """Marks of the windows that a smaller document also has, by a family of suffix arrays per part of a deal."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        teller = Teller()
        for deal, blobs, _ in _blocks(batches, 1 << 62):
            heads, bodies = [], []
            for _, blob in blobs:
                n = int(np.frombuffer(blob, np.int64, 1)[0])
                heads.append(np.frombuffer(blob, HEAD, n, 8))
                bodies.append(np.frombuffer(blob, np.uint8, -1, 8 + n * HEAD.itemsize))
            head, body = np.concatenate(heads), np.concatenate(bodies)
            del blobs, heads, bodies
            length = head["wide"].astype(np.int64) + span
            start = np.cumsum(length) - length
            by = np.argsort(head["sub"], kind="stable")
            cuts = np.searchsorted(head["sub"][by], np.arange(257))
            k = 0
            while k < 256:  # parts of a deal that together have a few batches
                to = max(k + 1, int(np.searchsorted(cuts, cuts[k] + 2 * BATCH, side="right")) - 1)
                mine = by[cuts[k] : cuts[to]]
                k = to
                if not len(mine):
                    continue
                for row, a, b in judged(body, start[mine], head[mine], span):
                    if len(row):
                        seen = told_of(head[mine[row]], deal)
                        seen["first"] += a.astype(np.uint32)
                        seen["wide"] = b - a
                        yield from teller.add(seen, True)
        yield from teller.flush()

    return dealt.mapInArrow(run, _told_schema)


def cut_out(rows: DataFrame, span: int, names: list[str], as_text: bool = False) -> DataFrame:
    """What is left of every text: adds kept, n_bytes, n_removed, n_spans and the removed runs.

    `kept` is binary, or with `as_text` a string without the fragments of characters that a cut goes through.
    """
    n = len(names)

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        body, off = utf8(batch, "_body")
        lists, (spots, ends) = batch.column(n + 1), utf8(batch, "spots")
        spots = spots.view(SPOT)
        owner = np.repeat(np.arange(len(lists)), np.diff(ends) // SPOT.itemsize)
        at = off[owner] + spots["first"]
        by = np.argsort(at, kind="stable")
        at, owner, to = at[by], owner[by], (at + spots["wide"] + span)[by]
        reach = np.maximum.accumulate(to) if len(to) else to
        new = np.ones(len(at), bool)
        new[1:] = (at[1:] > reach[:-1]) | (owner[1:] != owner[:-1])
        cut = np.flatnonzero(new)
        begins, doc = at[cut], owner[cut]
        stops = reach[np.append(cut[1:], len(at)) - 1] if len(cut) else begins
        edge = np.zeros(len(body) + 1, np.int8)
        edge[begins] += 1
        edge[stops] -= 1
        gone = np.cumsum(edge, dtype=np.int8)[: len(body)] > 0
        removed = np.bincount(doc, stops - begins, minlength=len(lists)).astype(np.int64)
        spans = np.bincount(doc, minlength=len(lists))
        first_run = np.concatenate([[0], np.cumsum(spans)])
        kept_off = np.concatenate([[0], np.cumsum(np.diff(off) - removed)])
        kept = pa.BinaryArray.from_buffers(pa.binary(), len(lists), [None, pa.py_buffer(kept_off.astype(np.int32).tobytes()), pa.py_buffer(body[~gone].tobytes())])
        if as_text:
            kept = pa.array([b.decode("utf-8", "ignore") for b in kept.to_pylist()], pa.string())
        runs = pa.StructArray.from_arrays([pa.array(begins - off[doc]), pa.array(stops - off[doc])], ["start", "stop"])
        lists_of = pa.ListArray.from_arrays(pa.array(first_run.astype(np.int32)), runs)
        cols = [batch.column(i) for i in range(n)]
        return pa.RecordBatch.from_arrays([*cols, kept, pa.array(np.diff(off)), pa.array(removed), pa.array(spans.astype(np.int64)), lists_of], [*names, "kept", "n_bytes", "n_removed", "n_spans", "removed"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*names).schema)
    schema += f", kept {'string' if as_text else 'binary'}, n_bytes long, n_removed long, n_spans long, removed array<struct<start:long,stop:long>>"
    return map_parts(rows.select(*names, "_body", "spots"), "_body", part, schema, 2 << 20)


def marked(texts: DataFrame, entries: DataFrame, deals: int, span: int, block: int = BLOCK) -> DataFrame:
    """(_order, _text_hash, spots): what to cut out of each text. `entries` has (deal, blob, old); `texts` all their texts."""
    found = settle(met(dealt_out(entries, deals), block), "anchors", last=True)
    wishes = asked(texts.select("_order", "_text_hash", "_body"), found.where("not mark"), deals)
    by_anchor = dealt_out(fetched(wishes, deals, span), deals)
    marks = by_text(found.where("mark").unionByName(scanned(by_anchor, span)), deals)
    out = settle(marks, "marks", last=True)
    discard(found)
    return out


def _base(docs: DataFrame, names: list[str], id_col: str, text: str) -> DataFrame:
    body = F.coalesce(F.col(text), F.lit("")).cast("binary")
    return docs.select(*(F.col(c).alias(f"_keep{i}") for i, c in enumerate(names)), order_key(id_col).alias("_order"), F.xxhash64(body).alias("_text_hash"), body.alias("_body"))


def _left(texts: DataFrame, marks: DataFrame, span: int, names: list[str], as_text: bool) -> DataFrame:
    rows = texts.join(marks.hint("shuffle_hash"), ["_order", "_text_hash"], "left")
    out = cut_out(rows, span, [f"_keep{i}" for i in range(len(names))], as_text)
    return out.select(*(F.col(f"_keep{i}").alias(c) for i, c in enumerate(names)), "kept", "n_bytes", "n_removed", "n_spans", "removed")


def _check(span: int, gram: int) -> None:
    if span < 3 * gram or span + gram > 240:
        raise ValueError("the span must be at least three grams and fit one byte with one more")


def dedup(docs: DataFrame, span: int = SPAN, id_col: str = "doc_id", text: str = "text", keep: list[str] | None = None, gram: int = GRAM, as_text: bool = False, block: int = BLOCK) -> DataFrame:
    """Every row of `docs` with kept (bytes or text), n_bytes, n_removed, n_spans and removed (runs of bytes)."""
    _check(span, gram)
    names = keep if keep is not None else [id_col]
    base = _base(docs, names, id_col, text)
    deals = deals_of(base)
    entries = anchored(base, deals, span, gram).withColumn("old", F.lit(False))
    return _left(base, marked(base, entries, deals, span, block), span, names, as_text)


class SuffixIndex:
    """The family as tables under `path`, for a corpus that arrives in batches whose ids exceed all earlier ones.

    texts/batch=b   (_order, _text_hash, _body) of a batch
    levels/<name>   (deal, blob): sorted anchored contexts of the batches that were merged into the level
    manifest/<b>    (place, name, contexts) of the levels after batch b, the largest first
    """

    def __init__(self, spark: SparkSession, path: str, deals: int = 64, span: int = SPAN, gram: int = GRAM):
        _check(span, gram)
        self.spark, self.path, self.deals, self.span, self.gram = spark, path.rstrip("/"), deals, span, gram

    def levels(self, batch: int) -> list[tuple[str, int]]:
        """(name, contexts) of the levels after a batch; before the first there are none."""
        if batch < 0:
            return []
        rows = self.spark.read.schema("place int, name string, contexts long").parquet(f"{self.path}/manifest/{batch}").collect()
        return [(r["name"], r["contexts"]) for r in sorted(rows, key=lambda r: r["place"])]

    def _level(self, name: str) -> DataFrame:
        return self.spark.read.schema("deal int, blob binary").parquet(f"{self.path}/levels/{name}")

    def _write(self, rows: DataFrame, name: str) -> int:
        """Writes a level, one sorted array for each deal, and tells its size."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for deal, blobs, _ in _blocks(batches, 1 << 30):
                own = np.concatenate([np.frombuffer(blob, ENTRY) for _, blob in blobs])
                own = own[own["state"] != KNOWN]  # an earlier context of the same part stands for it
                own = own[np.lexsort((own["order"], own["anchor"]))]
                yield pa.RecordBatch.from_arrays([pa.array([deal], pa.int32()), pa.array([own.tobytes()], pa.binary())], ["deal", "blob"])

        sorted_rows = dealt_out(rows.select("deal", "blob"), self.deals).mapInArrow(run, "deal int, blob binary")
        sorted_rows.write.mode("overwrite").parquet(f"{self.path}/levels/{name}")
        size = self._level(name).agg(F.sum(F.octet_length("blob").cast("long"))).first()[0] or 0
        return size // ENTRY.itemsize

    def add(self, docs: DataFrame, batch: int, id_col: str = "doc_id", text: str = "text", keep: list[str] | None = None, as_text: bool = False) -> DataFrame:
        """Judges batch number `batch` (from 0) against all before it, as `dedup` would judge them together, and indexes it.

        Adding a batch again overwrites what it wrote.
        """
        names = keep if keep is not None else [id_col]
        base = _base(docs, names, id_col, text)
        before = self.levels(batch - 1)
        base.select("_order", "_text_hash", "_body").write.mode("overwrite").parquet(f"{self.path}/texts/batch={batch}")
        entries = settle(anchored(base, self.deals, self.span, self.gram), "entries")
        known = entries.withColumn("old", F.lit(False))
        texts = base.select("_order", "_text_hash", "_body")
        for name, _ in before:
            known = known.unionByName(self._level(name).withColumn("old", F.lit(True)))
        for b in range(batch):
            texts = texts.unionByName(self.spark.read.schema("_order long, _text_hash long, _body binary").parquet(f"{self.path}/texts/batch={b}"))
        marks = marked(texts, known, self.deals, self.span)
        out = settle(_left(base, marks, self.span, names, as_text), "kept", last=True)
        discard(marks)
        # the batch becomes a level; levels of like size become one
        own = f"b{batch}-{uuid.uuid4().hex[:8]}"
        levels = [*before, (own, self._write(entries, own))]
        while len(levels) > 1 and levels[-2][1] < 2 * levels[-1][1]:
            (x, _), (y, _) = levels.pop(), levels.pop()
            name = f"m{batch}-{uuid.uuid4().hex[:8]}"
            levels.append((name, self._write(self._level(x).unionByName(self._level(y)), name)))
        discard(entries)
        rows = [(k, name, n) for k, (name, n) in enumerate(levels)]
        self.spark.createDataFrame(rows, "place int, name string, contexts long").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/manifest/{batch}")
        return out
