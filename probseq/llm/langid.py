"""Language identification by prediction with partial matching.

Each language has a tree of byte contexts of every length up to ORDER with frozen statistics. A byte that was seen after
its context costs log2((n + q) / n_b) bits, with n bytes and q distinct ones seen there; an unseen byte pays the escape
log2((n + q) / q) and is coded in the next shorter context, down to equal odds for all 256 bytes. A context without
statistics passes on for nothing. The code length of a text under a language is exact for those statistics, and the
language with the shortest code wins.

The trees are sparse: sorted keys of the contexts and grams (context and next byte) that any language has seen, with the
cost of each under every language, escapes to shorter contexts included. A byte is looked up from its longest context
down to the first gram that is known; what it passes on the way pays its escapes.

Fitting reads a bounded sample of labelled documents (about `per_language` of each language, chosen by hash, of at most
`byte_limit` bytes each, and together `total_bytes` a language) in one task of an executor; the driver gets the finished
tables. Everything else is scored whole, in blocks of bounded size. Defined results: null texts and texts without a letter
are `und` with score 0; with nothing to learn from, all texts are `und`; of equal code lengths the first language by name
wins; equal texts, repeated rows too, have equal results; an empty table gives no rows. Where a kept column is named like
a result, the kept column stays and the result goes.
"""

from __future__ import annotations

import io
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import in_one_task, map_parts, utf8

UNKNOWN = "und"
ORDER = 5
SHARP = 8.0  # bits a byte of lead are scaled by this before the score
BLOCK = 1 << 18  # bytes that are looked up at once
START = ord("\n")  # stands before the first byte of every text


@dataclass
class Level:
    """What is known of contexts of one length: grams with their costs, and contexts with their escapes."""

    grams: np.ndarray  # sorted keys: context bytes, then the byte that follows
    costs: np.ndarray  # (grams, languages) bits
    contexts: np.ndarray  # sorted keys
    escapes: np.ndarray  # (contexts, languages) bits; 0 where the language never saw the context


@dataclass
class Trees:
    languages: list[str]
    levels: list[Level]  # by context length, from 0
    rate: np.ndarray  # bits a byte that nearly all of a language's own held back texts stay under

    def pack(self) -> bytes:
        out = io.BytesIO()
        parts = {f"{name}{k}": getattr(x, name) for k, x in enumerate(self.levels) for name in ("grams", "costs", "contexts", "escapes")}
        np.savez(out, languages=np.array(self.languages), rate=self.rate, **parts)
        return out.getvalue()

    @staticmethod
    def unpack(data: bytes) -> Trees:
        z = np.load(io.BytesIO(data))
        levels = [Level(*(z[f"{name}{k}"] for name in ("grams", "costs", "contexts", "escapes"))) for k in range(sum(1 for f in z.files if f.startswith("grams")))]
        return Trees([str(x) for x in z["languages"]], levels, z["rate"])


def keys(body: np.ndarray, at: np.ndarray, back: int) -> np.ndarray:
    """The `back` bytes before each place and the byte there, as one number."""
    out = np.zeros(len(at), np.uint64)
    for k in range(back, -1, -1):
        out = (out << np.uint64(8)) | body[at - k]
    return out


def _places(sorted_keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.searchsorted(sorted_keys, wanted)
    at[at == len(sorted_keys)] = 0
    return at, sorted_keys[at] == wanted if len(sorted_keys) else np.zeros(len(wanted), bool)


def _led(texts: list[bytes], order: int) -> tuple[np.ndarray, np.ndarray]:
    """(texts one after the other, each behind `order` start bytes, places of their own bytes)."""
    lead = bytes([START]) * order
    body = np.frombuffer(b"".join(lead + t for t in texts), np.uint8)
    sizes = np.array([len(t) + order for t in texts], np.int64)
    own = np.ones(len(body), bool)
    for k in range(order):
        own[np.cumsum(sizes) - sizes + k] = False
    return body, np.flatnonzero(own)


def grow(samples: dict[str, list[bytes]], order: int = ORDER, held: dict[str, list[bytes]] | None = None) -> Trees:
    """Trees from sample texts; `held` texts, which taught nothing, set each language's usual rate."""
    languages = sorted(samples)
    led = [_led(samples[name], order) for name in languages]
    levels: list[Level] = []
    for k in range(order + 1):
        seen = [np.unique(keys(body, at, k), return_counts=True) for body, at in led]
        grams = np.unique(np.concatenate([g for g, _ in seen])) if seen else np.zeros(0, np.uint64)
        owner = np.unique(grams >> np.uint64(8), return_inverse=True)
        contexts, of = owner[0], owner[1].ravel()
        costs = np.zeros((len(grams), len(languages)), np.float32)
        escapes = np.zeros((len(contexts), len(languages)), np.float32)
        if k == 0:
            below = np.full((len(grams), len(languages)), 8.0)
        else:  # the gram without its first byte was counted, too
            below = levels[-1].costs[_places(levels[-1].grams, grams & np.uint64((1 << (8 * k)) - 1))[0]]
        for j, (own, count) in enumerate(seen):
            n_b = np.zeros(len(grams))
            n_b[np.searchsorted(grams, own)] = count
            n, q = np.bincount(of, n_b, len(contexts)), np.bincount(of, n_b > 0, len(contexts))
            with np.errstate(divide="ignore", invalid="ignore"):
                escape = np.where(n > 0, np.log2((n + q) / np.maximum(q, 1)), 0.0)
                costs[:, j] = np.where(n_b > 0, np.log2((n + q)[of] / n_b), escape[of] + below[:, j])
            escapes[:, j] = escape
        levels.append(Level(grams, costs, contexts, escapes))
    trees = Trees(languages, levels, np.full(len(languages), np.inf))
    for j, name in enumerate(languages):
        texts = [t for t in (held or {}).get(name, []) if t]
        if texts:
            off = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
            rates = code_lengths(trees, np.frombuffer(b"".join(texts), np.uint8), off).min(axis=1) / np.diff(off)
            trees.rate[j] = float(np.quantile(rates, 0.99))
    return trees


def _bits(trees: Trees, body: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Bits of the bytes at the given places under every language."""
    out = np.zeros((len(at), len(trees.languages)))
    left = np.arange(len(at))
    key = keys(body, at, len(trees.levels) - 1)
    for k in range(len(trees.levels) - 1, -1, -1):
        level = trees.levels[k]
        own = key[left] & np.uint64((1 << (8 * (k + 1))) - 1)
        place, hit = _places(level.grams, own)
        out[left[hit]] += level.costs[place[hit]]
        left, own = left[~hit], own[~hit]
        place, hit = _places(level.contexts, own >> np.uint64(8))
        out[left[hit]] += level.escapes[place[hit]]
        if not len(left):
            break
    out[left] += 8.0
    return out


def code_lengths(trees: Trees, body: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Bits of every text (rows) under every language (columns)."""
    order, length = len(trees.levels) - 1, np.diff(off)
    out = np.zeros((len(length), len(trees.languages)))
    filled = np.flatnonzero(length > 0)
    if not len(filled):
        return out
    lead = np.full(order, START, np.uint8)
    at = 0
    while at < len(filled):  # texts of about a block together; a longer text block by block
        to = max(at + 1, int(np.searchsorted(off[filled + 1], off[filled[at]] + BLOCK, side="right")))
        docs = filled[at:to]
        if len(docs) == 1:
            a, b = int(off[docs[0]]), int(off[docs[0] + 1])
            for start in range(a, b, BLOCK):
                stop = min(b, start + BLOCK)
                part = np.concatenate([lead, body[a:stop]]) if start - a < order else body[start - order : stop]
                skip = order + (start - a if start - a < order else 0)
                out[docs[0]] += _bits(trees, part, np.arange(skip, len(part))).sum(axis=0)
        else:
            sizes = length[docs] + order
            begin = np.cumsum(sizes) - sizes
            own = np.ones(int(sizes.sum()), bool)
            own[(begin[:, None] + np.arange(order)).ravel()] = False
            led = np.full(len(own), START, np.uint8)
            places = np.flatnonzero(own)
            led[places] = body[off[docs[0]] : off[docs[-1] + 1]]  # empty texts between add nothing
            out[docs] = np.add.reduceat(_bits(trees, led, places), begin - order * np.arange(len(docs)), axis=0)
        at = to
    return out


def share_of(label: str, counts: dict, per_label: int) -> Column:
    """Whether a row's hash falls in the share of its label that makes about `per_label` rows."""
    out = F.lit(False)
    for value, n in counts.items():
        out = out | ((F.col(label) == value) & (F.pmod("_hash", F.lit(1_000_000)) < min(1_000_000, -(-per_label * 1_000_000 // n))))
    return out


def row_hash(id_col: str, text: str) -> Column:
    return F.xxhash64(F.col(id_col).cast("string"), F.col(text)).alias("_hash")


def teachable(text: str, byte_limit: int) -> Column:
    return F.col(text).isNotNull() & (F.octet_length(text) <= byte_limit)


def sample(docs: DataFrame, usable: Column, label: str, per_label: int, byte_limit: int, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(label, text, hash) of about `per_label` usable rows of each label, by a hash of id and text; no shuffle but of counts."""
    rows = docs.where(usable & F.col(label).isNotNull() & teachable(text, byte_limit))
    counts = {r["_label"]: r["count"] for r in rows.groupBy(F.col(label).alias("_label")).count().collect()}
    return rows.select(F.col(label).alias("_label"), F.col(text).alias("_text"), row_hash(id_col, text)).where(share_of("_label", counts, per_label))


def fit(docs: DataFrame, usable: Column, lang: str = "lang", per_language: int = 400, byte_limit: int = 20_000, total_bytes: int = 400_000, id_col: str = "doc_id", text: str = "text") -> Trees | None:
    """Trees of a sample; a quarter of it grows no tree and sets the usual rates instead."""

    def learn(batches: Iterator[pa.RecordBatch]) -> bytes | None:
        rows = sorted((r for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True)), key=lambda r: (r[2], r[1]))
        taught: dict[str, list[bytes]] = {}
        held: dict[str, list[bytes]] = {}
        for label, body, h in rows:
            into = held if h % 4 == 1 else taught
            own = into.setdefault(label, [])
            if sum(map(len, own)) < total_bytes:
                own.append(body.encode())
        for label in held:  # nothing but held back texts: they teach
            if label not in taught:
                taught[label] = held[label]
        return grow(taught, held=held).pack() if any(t for v in taught.values() for t in v) else None

    made = in_one_task(sample(docs, usable, lang, per_language, byte_limit, id_col, text), learn)
    return Trees.unpack(made) if made else None


def predict(docs: DataFrame, trees: Trees | None, id_col: str = "doc_id", text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """(id[, kept columns], lang_pred, score, excess): the language of the shortest code, and its share among all.

    The score is the share of 2^(-SHARP * bits a byte) and is 0 for `und`. `excess` says how many times the bits a byte
    exceed the rate that nearly all of the language's own texts stay under.
    """
    own = keep if keep is not None else [id_col]
    made = [c for c in ("lang_pred", "score", "excess") if c not in own]
    shared = docs.sparkSession.sparkContext.broadcast(trees)
    more = [] if text in own else [F.col(text)]  # the text travels once
    rows = docs.select(*own, *more, F.coalesce(F.col(text).rlike(r"\p{L}"), F.lit(False)).alias("_letter"))

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        t = shared.value
        body, off = utf8(batch, text)
        letter = batch.column(batch.num_columns - 1).to_numpy(zero_copy_only=False)
        names, score, excess = np.full(batch.num_rows, UNKNOWN, object), np.zeros(batch.num_rows), np.zeros(batch.num_rows)
        if t is not None and letter.any():
            rate = code_lengths(t, body, off) / np.maximum(np.diff(off), 1)[:, None]
            best = rate.argmin(axis=1)
            low = rate[np.arange(len(best)), best]
            share = np.exp2(-SHARP * (rate - low[:, None]))
            names = np.where(letter, np.array(t.languages, object)[best], UNKNOWN)
            score = np.where(letter, 1 / share.sum(axis=1), 0.0)
            excess = np.where(letter, low / t.rate[best], 0.0)
        found = {"lang_pred": pa.array(names.tolist(), pa.string()), "score": pa.array(score), "excess": pa.array(excess)}
        return pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(own))), *(found[c] for c in made)], [*own, *made])

    schema = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*own).schema]
    schema += [f"{c} {'string' if c == 'lang_pred' else 'double'}" for c in made]
    return map_parts(rows, text, part, ", ".join(schema), 1 << 19)


def remainder(id_col: str, by: int) -> Column:
    """crc32 of the id as text, modulo `by`; null ids fall in no class."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % by
