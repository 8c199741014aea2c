"""One query per operator of this subpackage, each over its whole table with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probseq.llm.common import read

SHARDS = 24
WINDOW = 2048


def vocabulary(name: str) -> str:
    """Path of a public tokenizer file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids and decoded texts of all documents. A null text is the empty one: the end id alone."""
    from probseq.llm.sentencepieces import encode

    out = encode(read(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"))
    return out.select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.concat_ws(" ", F.col("ids").cast("array<string>")), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 24 shards, sizes near equal, equal texts together. Null texts have size 8; null ids are rows like others."""
    from probseq.llm.sharding import shard

    out = shard(read(spark, sf_dir, "documents"), SHARDS)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"), "slot", F.lit(None).cast("int").alias("grown_shard"))


def op3_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents as a stored Matroska column, parsed and read back by byte ranges. A null text is 64 zero bytes."""
    from probseq.llm.matroska import roundtrip

    return roundtrip(read(spark, sf_dir, "documents"))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is left of all documents once 50-byte strings of smaller ids are cut out. Null texts are empty; null ids come last."""
    from probseq.llm.suffixes import dedup

    return dedup(read(spark, sf_dir, "documents")).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in sequences of 2048 tokens. A null text is the end id alone."""
    from probseq.llm.packing import pack_documents

    out = pack_documents(read(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"), WINDOW, 1)
    return out.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


def op6_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of documents with similar 2-word shingles. Texts without words link with nothing; null ids come last."""
    from probseq.llm.minhash import link

    return link(read(spark, sf_dir, "documents"), words=2, num=80, den=100)


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages as WARC records, read back through the index. A null payload is empty; null ids come last."""
    from probseq.llm import warc

    index = warc.write(read(spark, sf_dir, "pages"))
    return warc.read(index).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A quality score for all documents. Empty and null texts are one blank passage; null ids are not held out."""
    from probseq.llm import quality
    from probseq.llm.langid import remainder

    docs = read(spark, sf_dir, "documents")
    held = F.coalesce(remainder("doc_id", 5) == 0, F.lit(False))
    model = quality.fit(docs, read(spark, sf_dir, "labels"), ~held)
    out = quality.score(docs, model)
    return out.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op9_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of all documents; `und` for null texts and those without a letter. Null ids are not held out."""
    from probseq.llm import langid

    docs = read(spark, sf_dir, "documents")
    held = F.coalesce(langid.remainder("doc_id", 4) == 2, F.lit(False))
    out = langid.predict(docs, langid.fit(docs, ~held))
    return out.select("doc_id", held.alias("held_out"), "lang_pred", "score")


def op10_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links between all vectors of a label. Null, zero and non-finite vectors link with nothing."""
    from probseq.llm.embeddings import link

    return link(read(spark, sf_dir, "embeddings"))


QUERIES = {
    "op1_sentencepiece": op1_sentencepiece,
    "op2_sharding": op2_sharding,
    "op3_media": op3_media,
    "op4_suffix_dedup": op4_suffix_dedup,
    "op5_packing": op5_packing,
    "op6_minhash": op6_minhash,
    "op7_warc": op7_warc,
    "op8_quality": op8_quality,
    "op9_langid": op9_langid,
    "op10_embeddings": op10_embeddings,
}

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

ORACLES: dict[str, str] = {
    # every 50-byte string in hexadecimal, the smallest id of each, then runs of covered bytes and what lies between them
    "op4_suffix_dedup": """WITH d AS MATERIALIZED (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
 w AS MATERIALIZED (SELECT doc_id, i, substring(h, 2 * i + 1, 100) AS s FROM (SELECT doc_id, h, unnest(range(0, length(h) // 2 - 49)) AS i FROM d)),
 f AS MATERIALIZED (SELECT s, min(doc_id) AS first FROM w GROUP BY s),
 hit AS (SELECT doc_id, i FROM w JOIN f USING (s) WHERE doc_id > first),
 run AS MATERIALIZED (SELECT doc_id, min(i) AS a, max(i) + 50 AS b FROM (SELECT doc_id, i, sum(fresh) OVER (PARTITION BY doc_id ORDER BY i) AS g FROM (SELECT doc_id, i, CASE WHEN i > lag(i) OVER (PARTITION BY doc_id ORDER BY i) + 50 THEN 1 ELSE 0 END AS fresh FROM hit)) GROUP BY doc_id, g),
 cut AS (SELECT doc_id, a, b FROM run UNION ALL SELECT doc_id, length(h) // 2, 0 FROM d),
 gap AS (SELECT doc_id, coalesce(max(b) OVER (PARTITION BY doc_id ORDER BY a, b DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS p, a AS q FROM cut),
 kept AS (SELECT g.doc_id, string_agg(substring(h, 2 * p + 1, 2 * greatest(q - p, 0)), '' ORDER BY q) AS k FROM gap g JOIN d USING (doc_id) GROUP BY g.doc_id),
 n AS (SELECT doc_id, sum(b - a) AS gone, count(*) AS spans FROM run GROUP BY doc_id)
 SELECT d.doc_id, (length(h) // 2)::BIGINT AS n_bytes, coalesce(gone, 0)::BIGINT AS n_removed, coalesce(spans, 0)::BIGINT AS n_spans, sha256(unhex(k)) AS kept_sha256 FROM d JOIN kept USING (doc_id) LEFT JOIN n USING (doc_id)""",
    # exact prefix join of all sets, then components by recursion
    "op6_minhash": f"""WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
 s AS MATERIALIZED (SELECT DISTINCT doc_id, CASE WHEN len(w) = 1 THEN w[1] ELSE w[k] || ' ' || w[k + 1] END AS x FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w), 2))) AS k FROM w WHERE len(w) > 0)),
 n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id), f AS (SELECT x, count(*) AS f FROM s GROUP BY x),
 p AS MATERIALIZED (SELECT doc_id, x, n FROM (SELECT s.doc_id, s.x, n.n, row_number() OVER (PARTITION BY s.doc_id ORDER BY f.f, s.x) AS r FROM s JOIN f USING (x) JOIN n USING (doc_id)) WHERE r <= n - ceil(n * 0.8) + 1),
 c AS MATERIALIZED (SELECT DISTINCT a.doc_id AS a, b.doc_id AS b, a.n AS na, b.n AS nb FROM p a JOIN p b ON a.x = b.x AND a.doc_id < b.doc_id AND least(a.n, b.n) * 100 >= greatest(a.n, b.n) * 80),
 l AS MATERIALIZED (SELECT c.a, c.b FROM c JOIN s x ON x.doc_id = c.a JOIN s y ON y.doc_id = c.b AND y.x = x.x GROUP BY c.a, c.b, c.na, c.nb HAVING 100 * count(*) >= 80 * (c.na + c.nb - count(*))),
 e AS MATERIALIZED (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
 r(id, c) AS (SELECT doc_id, doc_id FROM documents UNION SELECT e.b, r.c FROM r JOIN e ON e.a = r.id)
 SELECT d.doc_id, coalesce(any_value(n.n), 0)::BIGINT AS n_shingles, min(r.c) AS component_id, min(r.c) = d.doc_id AS kept FROM documents d JOIN r ON r.id = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id GROUP BY d.doc_id""",
    "op7_warc": """WITH d AS (SELECT page_id, strlen(coalesce(html, '')) AS n, sha256(coalesce(html, '')) AS h FROM pages), g AS (SELECT h, min(page_id) AS f FROM d WHERE n >= 100 GROUP BY h)
 SELECT page_id, n::BIGINT AS payload_bytes, h AS payload_digest, CASE WHEN page_id > f THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN page_id > f THEN f END AS refers_to FROM d LEFT JOIN g USING (h)""",
    "op10_embeddings": """WITH RECURSIVE v AS MATERIALIZED (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings),
 l AS MATERIALIZED (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id WHERE list_dot_product(a.e, b.e) / sqrt(list_dot_product(a.e, a.e) * list_dot_product(b.e, b.e)) >= 0.98),
 r(id, c) AS (SELECT vec_id, vec_id FROM v UNION SELECT l.b, r.c FROM r JOIN l ON l.a = r.id), k AS (SELECT a, count(*) AS n FROM l GROUP BY a)
 SELECT v.vec_id, coalesce(any_value(k.n), 0)::BIGINT AS n_links, min(r.c) AS component_id, min(r.c) = v.vec_id AS kept FROM v JOIN r ON r.id = v.vec_id LEFT JOIN k ON k.a = v.vec_id GROUP BY v.vec_id""",
}
