"""SentencePiece encoding and decoding through a table of distinct chunks.

No piece of the models that this serves has a white space marker after another character, so merges never cross the
start of a run of markers. A text is cut there, the distinct chunks of a part are looked up in a table of chunks, those
that are new are segmented once, and ids are joined back by position with one gather. The table lives in the worker and
grows from part to part: one for the corpus would need one shuffled row for each word of the corpus, far more than the
text itself, or a second scan of all texts. `segmented` counts what went through the model: as many chunks as are
distinct, as long as these fit the bound. Beyond it chunks are dropped after the part that brought them.

A model that crosses markers, folds characters, squeezes white space or adds no marker in front is refused.

Defined results: a null text is encoded as the empty one; the empty text has the end id only; very long words are
segmented but not kept in the table; repeated rows give repeated results; an empty table gives no rows; other columns are
left alone.
"""

from __future__ import annotations

import re
from itertools import chain, islice, pairwise
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import gather, list_array, map_parts, resident

MARK = "▁"
_chunks = re.compile(f"{MARK}+[^{MARK}]*")


class ChunkTable(dict):
    """chunk -> slot; slots index starts and lengths in one flat id array, and the decoded surface of the chunk."""

    def __init__(self, proto: bytes, chunk_limit: int = 120_000, byte_limit: int = 32 << 20):
        super().__init__()
        import sentencepiece

        self.sp = sentencepiece.SentencePieceProcessor(model_proto=proto)
        pieces = [self.sp.id_to_piece(i) for i in range(self.sp.get_piece_size())]
        if any(MARK in p.lstrip(MARK) for p in pieces):
            raise ValueError("this model has pieces that cross white space markers")
        # what a chunk by itself and a chunk within its text must have in common
        for probe in ("a", "a  b", " a", "a ", "\ufb01 \u2460 \uff21", "e\u0301 \u00e9", "a\tb\nc\u00a0d\u3000e\u200bf"):
            ids = self.sp.encode(probe)
            if self.sp.decode(ids) != probe or not self.sp.id_to_piece(ids[0]).startswith(MARK):
                raise ValueError("this model rewrites texts before it segments them")
        self.segmented = 0
        self.anchor = next(i for i, p in enumerate(pieces) if len(p) == 1 and p.isalpha() and p.isascii())
        self.chunk_limit, self.byte_limit = chunk_limit, byte_limit
        self.pieces = [p.replace(MARK, " ") for p in pieces]
        self.first_piece = 1 + max(i for i in range(len(pieces)) if self.sp.is_byte(i) or self.sp.is_control(i) or self.sp.is_unknown(i))
        self.pending, self.lengths, self.surfaces, self.held, self.flat = [], [1], [""], 0, np.array([self.sp.eos_id()], np.int32)

    def __missing__(self, chunk: str) -> int:
        slot = self[chunk] = len(self) + 1
        self.pending.append(chunk)
        return slot

    def grow(self) -> None:
        """Segments the pending chunks; encode() puts one marker before its input, so each goes in without its first."""
        new, self.pending = self.pending, []
        if not new:
            return
        self.segmented += len(new)
        lone, pieces = self.sp.piece_to_id(MARK), self.pieces
        made = self.sp.encode([c[1:].replace(MARK, " ") for c in new], num_threads=1)
        parts = [ids if ids else [lone] for ids in made]
        for ids in parts:
            if min(ids) < self.first_piece:  # byte pieces are decoded by the library
                self.surfaces.append(self.sp.decode([self.anchor, *ids])[1:])
            else:
                self.surfaces.append("".join([pieces[i] for i in ids]))
        self.lengths += map(len, parts)
        self.flat = np.concatenate([self.flat, np.fromiter(chain.from_iterable(parts), np.int32)])
        self.held += sum(map(len, new)) * 3

    def trim(self) -> None:
        """Back to the chunks that stay."""
        if self.held > self.byte_limit:
            self.chunk_limit = min(self.chunk_limit, len(self))
        if len(self) > self.chunk_limit:
            for chunk in list(islice(self, self.chunk_limit, None)):
                del self[chunk]
            del self.lengths[self.chunk_limit + 1 :]
            del self.surfaces[self.chunk_limit + 1 :]
            self.flat = self.flat[: sum(self.lengths)]

    def encode(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, list[str]]:
        """Flat ids, ids per text (end id included), decoded texts."""
        slots, stops, get = [], [0], self.__getitem__
        for text in texts:
            if text:
                slots += map(get, _chunks.findall(MARK + text.replace(" ", MARK)))
            slots.append(0)
            stops.append(len(slots))
        self.grow()
        surface = self.surfaces
        decoded = ["".join([surface[k] for k in slots[a:b]])[1:] for a, b in pairwise(stops)]
        lengths = np.array(self.lengths, np.int64)
        starts = np.cumsum(lengths) - lengths
        at = np.array(slots, np.int64)
        per = lengths[at]
        out = self.flat[gather(starts[at], per)], np.add.reduceat(per, stops[:-1]) if texts else np.zeros(0, np.int64), decoded
        self.trim()
        return out


def encode(docs: DataFrame, model: str, text: str = "text", ids: str = "ids", decoded: str = "decoded", id_col: str = "doc_id") -> DataFrame:
    """(id, ids array<int>, decoded string) of every row; `model` is the path of a SentencePiece model on the driver."""
    proto, owner = docs.sparkSession.sparkContext.broadcast(Path(model).read_bytes()), f"chunks of {model}"
    kind = docs.schema[id_col].dataType.simpleString()

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        table = resident(owner, lambda: ChunkTable(proto.value))
        flat, lengths, back = table.encode(batch.column(1).to_pylist())
        return pa.RecordBatch.from_arrays([batch.column(0), list_array(flat, lengths, pa.int32()), pa.array(back, pa.string())], [id_col, ids, decoded])

    return map_parts(docs.select(F.col(id_col), F.col(text).alias("_text")), "_text", part, f"{id_col} {kind}, {ids} array<int>, {decoded} string", owner=owner)


def decode(rows: DataFrame, model: str, ids: str = "ids", decoded: str = "decoded", id_col: str = "doc_id") -> DataFrame:
    """(id, decoded) of id arrays from anywhere; control ids decode to nothing, null to null."""
    proto = rows.sparkSession.sparkContext.broadcast(Path(model).read_bytes())
    kind = rows.schema[id_col].dataType.simpleString()

    def run(batches):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_proto=proto.value)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([None if x is None else sp.decode(x) for x in b.column(1).to_pylist()], pa.string())], [id_col, decoded])

    return rows.select(id_col, ids).mapInArrow(run, f"{id_col} {kind}, {decoded} string")
