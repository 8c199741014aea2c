"""Quality classifier: attention-based multiple-instance learning.

A document is a bag of passages of PASSAGE bytes. Each is encoded from its bytes alone: shares of byte classes, a hashed
histogram of byte pairs and its share of distinct byte quadruples. A hidden layer embeds it, gated attention
(tanh times sigmoid) weighs the passages of a document, and a logistic output scores their weighted mean. Labels stand at
documents only; the attention learns which passages give a document away.

Fitting reads a bounded sample (about `per_label` labelled documents of each value, chosen by hash, of at most
`byte_limit` bytes) in one task of an executor; the driver gets the finished weights. Scoring reads every whole text, a
long one in stretches of STRETCH bytes. Each class counts by its share among all labelled rows.
Defined results: null and empty texts are one blank passage; with no usable labels the score is 0.5; labels that
are null or disagree for one document do not teach; equal texts, repeated rows too, have equal scores; an empty table
gives no rows. Where a kept column is named score, it stays and the result goes.
"""

from __future__ import annotations

import io
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import by_sort, in_one_task, map_parts, utf8
from probseq.llm.langid import row_hash, share_of, teachable

PASSAGE = 256
PAIRS = 128
HIDDEN, GATE = 32, 16
STRETCH = 1 << 20  # bytes whose features are held at once; a multiple of PASSAGE

_classes = np.full(256, 10)
for _k, _span in enumerate((b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" ", b"\n", b".,;:", b"!?", b"#$%&*@", b"|/\\<>[]{}()=+_~^", b"'\"-`")):
    _classes[list(_span)] = _k
_classes[128:192], _classes[192:] = 11, 12
CLASSES = 13
WIDTH = CLASSES + PAIRS + 2


def passages(body: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(features of all passages, first passage of each document); an empty document has one blank passage."""
    length = np.diff(off)
    many = np.maximum(1, -(-length // PASSAGE))
    first = np.cumsum(many) - many
    total = int(many.sum())
    x = np.zeros((total, WIDTH), np.float32)
    if len(body):
        doc = np.repeat(np.arange(len(length)), length)
        place = np.arange(len(body)) - off[:-1][doc]
        own = first[doc] + place // PASSAGE
        size = np.bincount(own, minlength=total)
        n = np.maximum(size, 1).astype(np.float32)[:, None]
        x[:, :CLASSES] = np.bincount(own * CLASSES + _classes[body], minlength=total * CLASSES).reshape(total, CLASSES) / n
        b = body.astype(np.uint32)
        pair = (((b[:-1] << 8) | b[1:]) * np.uint32(2654435761)) >> np.uint32(25)
        same = own[:-1] == own[1:]
        x[:, CLASSES : CLASSES + PAIRS] = np.sqrt(np.bincount(own[:-1][same] * PAIRS + pair[same], minlength=total * PAIRS).reshape(total, PAIRS) / n)
        quad = (b[:-3] * np.uint32(0x01000193) ^ b[1:-2] * np.uint32(0x85EBCA6B) ^ b[2:-1] * np.uint32(0xC2B2AE35) ^ b[3:] * np.uint32(0x27D4EB2F)) if len(b) > 3 else b[:0]
        whole = own[: len(quad)] == own[3:] if len(b) > 3 else np.zeros(0, bool)
        key = np.sort((own[: len(quad)][whole].astype(np.uint64) << np.uint64(32)) | quad[whole])
        if len(key):
            new = np.concatenate([[True], key[1:] != key[:-1]])
            at = (key >> np.uint64(32)).astype(np.int64)
            x[:, -2] = np.bincount(at[new], minlength=total) / np.maximum(np.bincount(at, minlength=total), 1)
        x[:, -1] = size / PASSAGE
    return x, first


@dataclass
class Model:
    shift: np.ndarray
    scale: np.ndarray
    w: list[np.ndarray]  # hidden weights and bias, gate pair, attention vector, output weights and bias

    def pack(self) -> bytes:
        out = io.BytesIO()
        np.savez(out, self.shift, self.scale, *self.w)
        return out.getvalue()

    @staticmethod
    def unpack(data: bytes) -> Model:
        z = np.load(io.BytesIO(data))
        shift, scale, *w = (z[f"arr_{k}"] for k in range(len(z.files)))
        return Model(shift, scale, w)


def _start(rng: np.random.Generator) -> list[np.ndarray]:
    r = lambda *s: (rng.standard_normal(s) * (1.0 / np.sqrt(s[0]))).astype(np.float32)
    return [r(WIDTH, HIDDEN), np.zeros(HIDDEN, np.float32), r(HIDDEN, GATE), r(HIDDEN, GATE), r(GATE), r(HIDDEN), np.zeros(1, np.float32)]


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def _hidden(w: list[np.ndarray], x: np.ndarray) -> np.ndarray:
    return np.maximum(x @ w[0] + w[1], 0)


def _attend(w: list[np.ndarray], h: np.ndarray, first: np.ndarray) -> dict:
    t, g = np.tanh(h @ w[2]), _sigmoid(h @ w[3])
    raw = (t * g) @ w[4]
    bag = np.repeat(np.arange(len(first)), np.diff(np.append(first, len(h))))
    e = np.exp(raw - np.maximum.reduceat(raw, first)[bag])
    a = e / np.add.reduceat(e, first)[bag]
    z = np.add.reduceat(a[:, None] * h, first, axis=0)
    return {"h": h, "t": t, "g": g, "a": a, "z": z, "bag": bag, "p": _sigmoid(z @ w[5] + w[6][0])}


def _forward(w: list[np.ndarray], x: np.ndarray, first: np.ndarray) -> dict:
    return _attend(w, _hidden(w, x), first)


def probabilities(model: Model, body: np.ndarray, off: np.ndarray) -> np.ndarray:
    """The score of every text; of long texts only the embeddings of passages are held, never all their features."""
    hidden, first, at, n = [], [], 0, 0
    while at < len(off) - 1:
        to = max(at + 1, int(np.searchsorted(off, off[at] + STRETCH, side="right")) - 1)
        for start in range(int(off[at]), max(int(off[at]) + 1, int(off[to])), STRETCH) if to == at + 1 else (int(off[at]),):
            stop = min(int(off[to]), start + STRETCH) if to == at + 1 else int(off[to])
            own = off[at : to + 1] - start if to > at + 1 else np.array([0, stop - start])
            x, begin = passages(body[start:stop], own)
            if start == off[at]:
                first.append(begin + n)
            hidden.append(_hidden(model.w, (x - model.shift) / model.scale))
            n += len(x)
        at = to
    return _attend(model.w, np.concatenate(hidden), np.concatenate(first))["p"].astype(np.float64)


def _gradients(w: list[np.ndarray], x: np.ndarray, first: np.ndarray, y: np.ndarray, weight: np.ndarray) -> list[np.ndarray]:
    f = _forward(w, x, first)
    h, t, g, a, z, bag = (f[k] for k in ("h", "t", "g", "a", "z", "bag"))
    do = ((f["p"] - y) * weight / weight.sum()).astype(np.float32)
    dz = do[:, None] * w[5]
    da = (dz[bag] * h).sum(axis=1)
    draw = a * (da - np.add.reduceat(a * da, first)[bag])
    dt, dg = draw[:, None] * w[4] * g * (1 - t * t), draw[:, None] * w[4] * t * g * (1 - g)
    dh = a[:, None] * dz[bag] + dt @ w[2].T + dg @ w[3].T
    dh[h <= 0] = 0
    return [x.T @ dh, dh.sum(axis=0), h.T @ dt, h.T @ dg, (t * g).T @ draw, z.T @ do, np.array([do.sum()], np.float32)]


def train(texts: list[bytes], labels: np.ndarray, weights: np.ndarray, epochs: int = 40, batch: int = 128, seed: int = 7) -> Model:
    """Adam on the logistic loss; deterministic for equal input."""
    rng = np.random.default_rng(seed)
    parts = []
    for k in range(0, len(texts), 64):  # features of a few documents at a time: the driver is small
        own = texts[k : k + 64]
        parts.append(passages(np.frombuffer(b"".join(own), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in own])]).astype(np.int64)))
    x = np.concatenate([p[0] for p in parts])
    begin = np.cumsum([0] + [len(p[0]) for p in parts])
    first = np.concatenate([p[1] + b for p, b in zip(parts, begin, strict=False)])
    del parts
    shift, scale = x.mean(axis=0), x.std(axis=0) + 1e-3
    x = (x - shift) / scale
    many = np.diff(np.append(first, len(x)))
    w = _start(rng)
    m, v, step = [np.zeros_like(p) for p in w], [np.zeros_like(p) for p in w], 0
    for epoch in range(epochs):
        rate = 0.004 * (1 - epoch / epochs) + 1e-4
        order = rng.permutation(len(texts))
        for k in range(0, len(order), batch):
            pick = order[k : k + batch]
            rows = np.concatenate([np.arange(first[d], first[d] + many[d]) for d in pick])
            begin = np.cumsum(many[pick]) - many[pick]
            step += 1
            for i, d in enumerate(_gradients(w, x[rows], begin, labels[pick], weights[pick])):
                d = d + 1e-5 * w[i]
                m[i] = 0.9 * m[i] + 0.1 * d
                v[i] = 0.999 * v[i] + 0.001 * d * d
                w[i] = w[i] - rate * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.999**step)) + 1e-8)
    return Model(shift, scale, [p.astype(np.float32) for p in w])


def fit(docs: DataFrame, labels: DataFrame, usable: Column, target: str = "quality", per_label: int = 1200, byte_limit: int = 20_000, id_col: str = "doc_id", text: str = "text") -> Model | None:
    """`usable` says, by columns of `docs`, which rows may teach."""
    taught = labels.where(F.col(target).isNotNull()).groupBy(F.col(id_col).alias("_id")).agg(F.min(target).alias("_low"), F.max(target).alias("_high")).where("_low = _high")
    # ids and hashes alone meet the labels; the texts of the few chosen ones are read in a second scan
    keyed = docs.where(usable & teachable(text, byte_limit)).select(F.col(id_col).alias("_id"), row_hash(id_col, text))
    rows = by_sort(keyed, taught.select("_id", F.col("_low").alias("_label")), "_id").select("_label", "_hash")
    shares = {r["_label"]: r["count"] for r in rows.groupBy("_label").count().collect()}
    if len(shares) < 2:
        return None
    chosen = rows.where(share_of("_label", shares, per_label)).distinct()  # about per_label rows of each label
    texts = docs.where(usable & teachable(text, byte_limit)).select(row_hash(id_col, text), F.col(text).alias("_text"))

    def learn(batches: Iterator[pa.RecordBatch]) -> bytes | None:
        got = sorted({(t.encode(), int(k)) for b in batches for t, k in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)})
        y = np.array([k for _, k in got], np.float32)
        weights = np.array([shares[k] / max(1, (y == k).sum()) for _, k in got], np.float32)
        return train([t for t, _ in got], y, weights).pack() if len(set(y.tolist())) > 1 else None

    made = in_one_task(texts.join(F.broadcast(chosen), "_hash").select("_text", "_label"), learn)
    return Model.unpack(made) if made else None


def score(docs: DataFrame, model: Model | None, id_col: str = "doc_id", text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """(id[, kept columns], score): the probability of label 1 of every document."""
    own = keep if keep is not None else [id_col]
    made = ["score"] if "score" not in own else []
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        m = shared.value
        p = np.full(batch.num_rows, 0.5) if m is None else probabilities(m, *utf8(batch, text))
        return pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(own))), *([pa.array(p)] if made else [])], [*own, *made])

    schema = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*own).schema] + [f"{c} double" for c in made]
    more = [] if text in own else [F.col(text)]  # the text travels once
    return map_parts(docs.select(*own, *more), text, part, ", ".join(schema), 1 << 19)


def attention(model: Model, text: bytes) -> np.ndarray:
    """The weight of every passage of one document."""
    x, first = passages(np.frombuffer(text, np.uint8), np.array([0, len(text)]))
    return _forward(model.w, (x - model.shift) / model.scale, first)["a"]
