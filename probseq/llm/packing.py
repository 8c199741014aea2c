"""Packing token sequences with best-fit decreasing.

Documents longer than a window are first cut into full windows; what remains of each is an item of 1..window tokens.
Items are placed by falling length into the open window with the least sufficient room. As lengths are small
integers, a segment tree indexed by remaining room finds that room, and all windows with the same room are placed at
once: the whole plan is a small table made from one count per length, whatever the number of documents. An item
finds its window by its rank among items of its length, so neither ids nor documents are gathered anywhere.

Defined results: a null text is an empty one, which is the end id alone; null ids and repeated rows are packed as
rows of their own; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import json
import os
import re
import unicodedata
import zlib
from itertools import islice
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import gather, list_array, map_parts, numbered, resident, settle

_split = re.compile(r"[^ \t\n\r\f\v]+")


def byte_letters() -> dict[int, str]:
    """The printable stand-in of every byte in byte-level vocabularies: itself where visible, else the next from U+0100."""
    seen = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(seen)]
    return {b: chr(b) for b in seen} | {b: chr(256 + k) for k, b in enumerate(rest)}


WHITE = " \t\n\v\f\r\x85\xa0"  # all white space below U+0250


class TokenTable(dict):
    """pre-token -> slot of its ids, for tokenizers that lower-case, split by the pattern of `spec` and merge byte letters.

    Texts of characters below U+0250 are cut by an equivalent pattern of the standard library, and new pre-tokens are
    merged many at a time: the merges of one always end with an end-of-word piece, which gives them back their borders.
    Words with other characters or special tokens take the tokenizer's own way. The first `limit` entries stay for the
    life of the worker; later ones are dropped after the part that brought them.
    """

    def __init__(self, spec: str, limit: int = 60_000):
        super().__init__()
        from tokenizers import Tokenizer, pre_tokenizers

        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core, and every thread of the library keeps an arena
        self.tokenizer, self.limit, self.letters = Tokenizer.from_str(spec), limit, byte_letters()
        made = json.loads(spec)
        cut = [x["pattern"]["Regex"] for x in made["pre_tokenizer"].get("pretokenizers", []) if x["type"] == "Split"]
        self.known = cut == [r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"] and made["model"]["end_of_word_suffix"] == "</w>"
        self.merger = Tokenizer(self.tokenizer.model)
        self.merger.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        vocab = made["model"]["vocab"]
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        kinds = {k: "".join(chr(c) for c in range(0x250) if unicodedata.category(chr(c))[0] == k) for k in "LN"}
        esc = {k: re.escape(v) for k, v in kinds.items()}
        self.pattern = re.compile(f"[{esc['L']}]+|'(?:s|t|re|ve|m|ll|d)|[{esc['N']}]|[^{WHITE}{esc['L']}{esc['N']}]+")
        self.odd = re.compile("[^\\x00-\u012f\u0131-\u024f]|<\\|")
        self.pending: list[str] = []
        self.lengths, self.held, self.flat = [], 0, np.zeros(0, np.uint32)

    def __missing__(self, token: str) -> int:
        slot = self[token] = len(self)
        self.pending.append(token)
        self.held += len(token)
        return slot

    def merged(self, token: str) -> str:
        return token if token.isascii() else token.encode().decode("latin-1").translate(self.letters)

    def grow(self) -> None:
        """Ids of the pending entries, at the end of the flat array."""
        new, self.pending = self.pending, []
        plain = [t for t in new if t[0] != " "]
        # few at a time, as what the library returns for a token takes far more room than its id
        made = []
        for i in range(0, len(plain), 4096):
            runs = [" ".join(map(self.merged, plain[k : k + 256])) for k in range(i, min(i + 4096, len(plain)), 256)]
            made += [np.array(e.ids, np.uint32) for e in self.merger.encode_batch_fast(runs, add_special_tokens=False)]
        ids = np.concatenate(made) if made else np.zeros(0, np.uint32)
        last = np.flatnonzero(self.ends[ids])
        per = np.diff(last, prepend=-1).tolist()
        if len(per) != len(plain) or len(plain) < len(new):  # words that the tokenizer takes whole, or pieces that it lacks
            own = [self.tokenizer.encode(t[1:] if t[0] == " " else t, add_special_tokens=False).ids for t in new]
            ids, per = np.array([x for e in own for x in e], np.uint32), [len(e) for e in own]
        self.flat = np.concatenate([self.flat, ids])
        self.lengths += per

    def trim(self) -> None:
        """Back to the entries that stay."""
        if self.held > 24 << 20:
            self.limit = min(self.limit, len(self))
        if len(self) > self.limit:
            for token in list(islice(self, self.limit, None)):
                del self[token]
            del self.lengths[self.limit :]
            self.flat = self.flat[: sum(self.lengths)]

    def cut(self, text: str) -> list[str]:
        if self.known and not self.odd.search(text):
            return self.pattern.findall(text.lower())
        out = []
        for word in _split.findall(text):
            if self.known and not self.odd.search(word):
                out += self.pattern.findall(word.lower())
            else:
                out.append(" " + word)  # taken whole
        return out

    def encode(self, texts: list[str | None], end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of all texts, each followed by `end_id`, and the number of ids of each."""
        slots, counts, get = [], np.zeros(len(texts), np.int64), self.__getitem__
        for k, text in enumerate(texts):
            if text:
                n = len(slots)
                slots += map(get, self.cut(text))
                counts[k] = len(slots) - n
        self.grow()
        lengths = np.array(self.lengths, np.int64)
        starts = np.cumsum(lengths) - lengths
        at = np.array(slots, np.int64)
        ids = self.flat[gather(starts[at], lengths[at])]
        before = np.concatenate([[0], np.cumsum(lengths[at])])
        stop = np.cumsum(counts)
        per = before[stop] - before[stop - counts]
        self.trim()
        return np.insert(ids, np.cumsum(per), end_id), per + 1


def windows(docs: DataFrame, tokenizer: str, window: int = 2048, end_id: int = 1, id_col: str = "doc_id", text: str = "text", with_ids: bool = True) -> DataFrame:
    """Pieces (id, start, length, ids_crc32, doc_tokens[, ids]) of all documents; every piece but a last one is full."""
    spec = docs.sparkSession.sparkContext.broadcast(Path(tokenizer).read_text(encoding="utf-8"))
    owner = f"tokens of {tokenizer} {end_id}"
    kind = docs.schema[id_col].dataType.simpleString()
    names = [id_col, "start", "length", "ids_crc32", "doc_tokens"] + ["ids"] * with_ids

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        table = resident(owner, lambda: TokenTable(spec.value))
        flat, counts = table.encode(batch.column(1).to_pylist(), end_id)
        pieces = -(-counts // window)
        doc = np.repeat(np.arange(len(counts)), pieces)
        start = (np.arange(len(doc)) - np.repeat(np.cumsum(pieces) - pieces, pieces)) * window
        length = np.minimum(window, counts[doc] - start)
        at = (np.cumsum(counts) - counts)[doc] + start
        raw = flat.astype("<u4").view(np.uint8).data
        crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(at.tolist(), (at + length).tolist(), strict=True)]
        cols = [batch.column(0).take(pa.array(doc)), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()), pa.array(counts[doc], pa.int64())]
        if with_ids:
            cols.append(list_array(flat.astype(np.int32), length, pa.int32()))
        return pa.RecordBatch.from_arrays(cols, names)

    schema = f"{id_col} {kind}, start long, length long, ids_crc32 long, doc_tokens long" + ", ids array<int>" * with_ids
    return map_parts(docs.select(F.col(id_col), F.col(text).alias("_text")), "_text", part, schema, 2 << 20, owner)


class RoomTree:
    """Segment tree over remaining rooms 0..size: the least room >= x that has open windows."""

    def __init__(self, size: int):
        self.leaves = 1 << size.bit_length()
        self.open = [False] * (2 * self.leaves)

    def mark(self, room: int, is_open: bool) -> None:
        i = room + self.leaves
        self.open[i] = is_open
        while i > 1:
            i //= 2
            self.open[i] = self.open[2 * i] or self.open[2 * i + 1]

    def tightest(self, room: int) -> int | None:
        i = room + self.leaves
        if self.open[i]:
            return room
        while i > 1:  # up to the first right neighbour with something open, then down its left edge
            if i % 2 == 0 and self.open[i + 1]:
                i += 1
                while i < self.leaves:
                    i = 2 * i if self.open[2 * i] else 2 * i + 1
                return i - self.leaves
            i //= 2
        return None


def best_fit_decreasing(counts: dict[int, int], window: int) -> list[tuple]:
    """counts: items per length -> (length, first rank, items per window, first window, windows, offset) rows.

    Item r of a length lies in row with first rank <= r; its window is first window + (r - first rank) // per and its
    place there is offset + ((r - first rank) % per) * length.
    """
    tree, spans, plan, made = RoomTree(window), {}, [], 0  # spans: room -> [(first window, windows)]

    def put(room: int, first: int, many: int) -> None:
        if many and room:
            spans.setdefault(room, []).append((first, many))
            tree.mark(room, True)

    for length in sorted((x for x, c in counts.items() if c), reverse=True):
        left, rank = counts[length], 0
        while left:
            room = tree.tightest(length)
            per = (room or window) // length
            if room is None:  # open as many new windows as the rest needs
                room, first, many = window, made, -(-left // per)
                made += many
            else:
                first, many = spans[room].pop()
                if not spans[room]:
                    tree.mark(room, False)
            full = min(many, left // per)
            if full:
                plan.append((length, rank, per, first, full, window - room))
                put(room - per * length, first, full)
                rank, left = rank + full * per, left - full * per
            if left and full < many:  # one window takes the last, fewer than `per`
                plan.append((length, rank, left, first + full, 1, window - room))
                put(room - left * length, first + full, 1)
                rank, left, full = rank + left, 0, full + 1
            put(room, first + full, many - full)
    return plan


def pack(pieces: DataFrame, window: int = 2048, id_col: str = "doc_id") -> DataFrame:
    """Adds sequence_id and offset to pieces (id, start, length, ...); ids of windows are gapless from 0."""
    spark = pieces.sparkSession
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    plan = best_fit_decreasing(counts, window)
    kind = "length long, low long, per long, first long, many long, place long"
    placed = spark.createDataFrame(plan or [(-1, 0, 1, 0, 0, 0)], kind).withColumn("high", F.col("low") + F.col("per") * F.col("many"))
    ranked = numbered(pieces, ["length"], F.struct(id_col, "start"), [F.col(id_col), F.col("start")], "rank")
    near = ranked["length"] == placed["length"]
    j = ranked.join(F.broadcast(placed), near & (F.col("rank") >= F.col("low")) & (F.col("rank") < F.col("high")))
    nth = F.col("rank") - F.col("low")
    return j.select(
        *(ranked[c] for c in pieces.columns),
        (F.col("first") + F.floor(nth / F.col("per"))).cast("long").alias("sequence_id"),
        (F.col("place") + (nth % F.col("per")) * ranked["length"]).cast("long").alias("offset"),
    )


def pack_documents(docs: DataFrame, tokenizer: str, window: int = 2048, end_id: int = 1, id_col: str = "doc_id", text: str = "text", with_ids: bool = False) -> DataFrame:
    """Tokenizes, cuts and packs; the pieces are written once, as the plan and the placing both read them."""
    return pack(settle(windows(docs, tokenizer, window, end_id, id_col, text, with_ids), "pieces"), window, id_col)


def sequences(packed: DataFrame, window: int = 2048, pad_id: int = 0) -> DataFrame:
    """(sequence_id, ids, used) from pieces with ids: joined by offset, padded to the window except at a power of two."""
    rows = packed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("_p"))
    flat = rows.select("sequence_id", F.flatten(F.transform("_p", lambda p: p["ids"])).alias("_ids")).withColumn("used", F.size("_ids"))
    keeps = F.expr("(used & (used - 1)) = 0")
    return flat.select("sequence_id", F.when(keeps, F.col("_ids")).otherwise(F.concat("_ids", F.array_repeat(F.lit(pad_id), F.lit(window) - F.col("used")))).alias("ids"), "used")
