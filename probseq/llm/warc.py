"""WARC archives with an index first: every record's offset, length, URL and digest is written before anything is read.

Pages become gzip members of WARC files in the shared folder, one file per writing task and bound of bytes. The index
is a table by itself (one row per record with file, offset and length); a reader sorts the selected rows by file and
offset, joins near byte ranges into one read, and parses the records in it.

Of records with equal payloads of at least `least` bytes, that with the smallest id is the response and others are
revisits that refer to it. Defined results: a null payload is the empty one; rows that share the smallest id are all
responses; a null id comes after all others and null rows of a group are responses only if no id is known; a null URL
is left out of the record. Rewritten files of a lost task get new names, and the index only names files of rows in it.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import by_sort, discard, order_key, settle, shared_folder

CRLF = b"\r\n"
DATE = "2024-01-01T00:00:00Z"  # pages carry no time of their own
GAP = 64 << 10  # ranges closer than this are read together
RANGE = 8 << 20  # bytes of a coalesced read
FILE = 256 << 20  # bytes after which a task begins another file
INDEX = "archive string, offset long, length long"


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One response or revisit record; a revisit keeps the HTTP head, which has the length of the payload."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if refers_to is not None else http + payload
    head = [
        ("WARC-Type", "response" if refers_to is None else "revisit"),
        ("WARC-Record-ID", f"<urn:page:{page_id}>"),
        ("WARC-Date", DATE),
        ("WARC-Payload-Digest", f"sha256:{digest}"),
        ("Content-Type", "application/http; msgtype=response"),
        ("Content-Length", str(len(block))),
    ]
    if url is not None:
        head.append(("WARC-Target-URI", url.replace("\r", "%0D").replace("\n", "%0A")))
    if refers_to is not None:
        head += [("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Refers-To", f"<urn:page:{refers_to}>")]
    return b"WARC/1.1\r\n" + b"".join(f"{k}: {v}\r\n".encode() for k, v in head) + CRLF + block + CRLF + CRLF


def parse(raw: bytes) -> dict:
    """Headers, HTTP head and payload of one record."""
    head, found, rest = raw.partition(CRLF + CRLF)
    first, *lines = head.split(CRLF)
    if not found or not first.startswith(b"WARC/"):
        raise ValueError("not a WARC record")
    headers = {k.decode().lower(): v.decode() for k, v in (x.split(b": ", 1) for x in lines)}
    block = rest[: int(headers["content-length"])]
    http, _, payload = block.partition(CRLF + CRLF)
    fields = {k.lower(): v for k, v in (x.split(b": ", 1) for x in http.split(CRLF)[1:])}
    return {"headers": headers, "http": fields, "payload": payload}


def gzip_member(raw: bytes, level: int) -> bytes:
    c = zlib.compressobj(level, zlib.DEFLATED, 31)
    return c.compress(raw) + c.flush()


def _id(value: str) -> int | None:
    text = value.removeprefix("<urn:page:").removesuffix(">")
    return None if text == "None" else int(text)


def originals(pages: DataFrame, id_col: str, payload: str, least: int) -> DataFrame:
    """(id, digest, refers_to) of the rows that are revisits: rows with a smaller id of the same payload."""
    body = F.coalesce(F.col(payload), F.lit("")).cast("binary")
    sums = pages.select(F.col(id_col).alias("_id"), F.sha2(body, 256).alias("_digest"), F.octet_length(body).alias("_n")).where(F.col("_n") >= least)
    first = sums.groupBy("_digest").agg(F.min("_id").alias("_first"), F.count(F.lit(1)).alias("_many")).where((F.col("_many") > 1) & F.col("_first").isNotNull())
    found = by_sort(sums, first, "_digest").where(order_key("_id") > F.col("_first"))
    return settle(found.select("_id", "_digest", "_first").distinct(), "revisits")


def write(pages: DataFrame, id_col: str = "page_id", url: str = "url", payload: str = "html", least: int = 100, level: int = 5) -> DataFrame:
    """Writes the archives and settles the index: (id, url, digest, record_type, archive, offset, length)."""
    folder = f"{shared_folder(pages.sparkSession)}/warc-{uuid.uuid4().hex}"
    kind = pages.schema[id_col].dataType.simpleString()
    body = F.coalesce(F.col(payload), F.lit("")).cast("binary")
    revisits = originals(pages, id_col, payload, least)
    rows = pages.select(F.col(id_col).alias("_page"), F.col(url).cast("string").alias("_url"), body.alias("_body"))
    near = rows["_page"].eqNullSafe(revisits["_id"]) & (F.sha2(rows["_body"], 256) == revisits["_digest"]) if _has_repeats(pages, id_col) else rows["_page"] == revisits["_id"]
    rows = rows.join(revisits, near, "left").select("_page", "_url", "_body", "_first")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs
        from pyspark import TaskContext

        store, root = fs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (fs.LocalFileSystem(), folder)
        store.create_dir(root, recursive=True)
        task = TaskContext.get()
        out = at = name = None
        done: list[tuple] = []

        def close():
            nonlocal out, done
            out.close()
            ready, out, done = done, None, []
            cols = list(zip(*ready, strict=True))
            types = [batch.schema.field(0).type, pa.string(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types, strict=True)], [id_col, "url", "digest", "record_type", "archive", "offset", "length"])

        for batch in batches:
            for page, link, data, first in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if out is None:
                    name = f"{root}/{task.partitionId():06d}-{task.taskAttemptId()}-{uuid.uuid4().hex[:8]}.warc.gz"
                    out, at = store.open_output_stream(name, compression=None), 0
                digest = hashlib.sha256(data).hexdigest()
                member = gzip_member(record(page, link, data, digest, first), level)
                out.write(member)
                done.append((page, link, digest, "response" if first is None else "revisit", name, at, len(member)))
                at += len(member)
                if at >= FILE:
                    yield close()
        if out is not None:
            yield close()

    index = rows.mapInArrow(run, f"{id_col} {kind}, url string, digest string, record_type string, {INDEX}")
    out = settle(index, "warc-index")
    discard(revisits)
    return out


def _has_repeats(pages: DataFrame, id_col: str) -> bool:
    """Whether an id is null or stands in several rows; then revisits are matched by payload too."""
    return bool(pages.groupBy(id_col).agg(F.count(F.lit(1)).alias("_n")).where((F.col("_n") > 1) | F.col(id_col).isNull()).limit(1).count())


def read(index: DataFrame, id_col: str = "page_id", where: Column | None = None, with_payload: bool = False) -> DataFrame:
    """Records of the selected index rows, through coalesced byte ranges.

    Rows are dealt by (archive, stretch of RANGE bytes) and sorted by offset, so each task reads forward.
    """
    spark = index.sparkSession
    base = shared_folder(spark)
    kind = index.schema[id_col].dataType.simpleString()
    chosen = index if where is None else index.where(where)
    stretch = F.floor(F.col("offset") / RANGE).alias("stretch")
    dealt = chosen.select(id_col, "digest", "archive", "offset", "length", stretch).repartition("archive", "stretch").sortWithinPartitions("archive", "offset")
    names = [id_col, "payload_bytes", "payload_digest", "record_type", "refers_to", "target_uri", "intact"] + ["payload"] * with_payload

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        store = fs.FileSystem.from_uri(base)[0] if "://" in base or base.startswith("file:") else fs.LocalFileSystem()
        source, opened = None, None
        for batch in batches:
            ids, digests, archives, offsets, lengths = (batch.column(i).to_pylist() for i in range(5))
            rows, i, n = [], 0, batch.num_rows
            while i < n:
                j = i + 1  # the rows that one read serves
                while j < n and archives[j] == archives[i] and offsets[j] <= offsets[j - 1] + lengths[j - 1] + GAP and offsets[j] + lengths[j] - offsets[i] <= RANGE:
                    j += 1
                if opened != archives[i]:
                    if source is not None:
                        source.close()
                    source, opened = store.open_input_file(archives[i]), archives[i]
                data = source.read_at(offsets[j - 1] + lengths[j - 1] - offsets[i], offsets[i])
                for k in range(i, j):
                    at = offsets[k] - offsets[i]
                    r = parse(zlib.decompress(data[at : at + lengths[k]], 31))
                    h, payload = r["headers"], r["payload"]
                    digest, revisit = h["warc-payload-digest"].removeprefix("sha256:"), h["warc-type"] == "revisit"
                    intact = digest == digests[k] and (revisit or hashlib.sha256(payload).hexdigest() == digest)
                    row = (_id(h["warc-record-id"]), int(r["http"][b"content-length"]), digest, h["warc-type"], _id(h["warc-refers-to"]) if revisit else None, h.get("warc-target-uri"), intact)
                    rows.append((*row, payload) if with_payload else row)
                i = j
            if rows:
                own = batch.schema.field(0).type
                types = [own, pa.int64(), pa.string(), pa.string(), own, pa.string(), pa.bool_()] + [pa.binary()] * with_payload
                yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names)
        if source is not None:
            source.close()

    schema = f"{id_col} {kind}, payload_bytes long, payload_digest string, record_type string, refers_to {kind}, target_uri string, intact boolean" + ", payload binary" * with_payload
    return dealt.mapInArrow(run, schema)
