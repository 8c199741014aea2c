"""A corpus pipeline: language, quality, near-duplicates, repeated passages, packing.

Each stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept and returns a DataFrame, which is
written as Parquet and read again as the next one's docs. All but the last return the columns of `documents`.
Other columns of docs, whatever their names, are passed on.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probseq.llm import langid, minhash, packing, quality, suffixes
from probseq.llm.common import read, settle, sweep
from probseq.llm.queries import WINDOW, vocabulary

FOREIGN, EVIDENCE = 1.75, 100  # times the usual bits a byte, over so many bytes
QUALITY = 0.3
WORDS, NUM, DEN = 5, 80, 100


def _plain(docs: DataFrame) -> tuple[DataFrame, list[str], dict[str, str]]:
    """docs under names that no operator uses, those names, and where each column went. What earlier stages held is swept."""
    sweep(docs.sparkSession)
    names = [f"_d{i}" for i in range(len(docs.columns))]
    return docs.toDF(*names), names, dict(zip(docs.columns, names, strict=True))


def _back(rows: DataFrame, docs: DataFrame) -> DataFrame:
    return rows.select(*(F.col(f"_d{i}").alias(c) for i, c in enumerate(docs.columns)))


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language of the corpus; those without a letter go, and those that no language's tree explains."""
    plain, names, at = _plain(docs)
    trees = langid.fit(plain, F.lit(True), lang=at["lang"], id_col=at["doc_id"], text=at["text"])
    found = langid.predict(plain, trees, text=at["text"], keep=names)
    foreign = (F.col("excess") > FOREIGN) & (F.octet_length(at["text"]) >= EVIDENCE)
    return _back(found.where((F.col("lang_pred") != langid.UNKNOWN) & ~foreign), docs)


def good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose quality score reaches the threshold."""
    plain, names, at = _plain(docs)
    labels = read(spark, sf_dir, "labels")
    model = quality.fit(plain, labels.select(F.col("doc_id").alias(at["doc_id"]), "quality"), F.lit(True), id_col=at["doc_id"], text=at["text"])
    scored = quality.score(plain, model, text=at["text"], keep=names)
    return _back(scored.where(F.col("score") >= QUALITY), docs)


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: that with the smallest id."""
    plain, names, at = _plain(docs)
    linked = minhash.link(plain, WORDS, NUM, DEN, id_col=at["doc_id"], text=at["text"], keep=names)
    return _back(linked.where("kept"), docs)


def fresh(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages of 50 bytes or more that an earlier document has."""
    plain, names, at = _plain(docs)
    left = suffixes.dedup(plain, id_col=at["doc_id"], text=at["text"], keep=names, as_text=True)
    changed = {"text": F.when(F.col("n_removed") > 0, F.col("kept")).otherwise(F.col(at["text"])), "n_chars": F.when(F.col("n_removed") > 0, F.length("kept").cast("long")).otherwise(F.col(at["n_chars"])) if "n_chars" in at else None}
    return left.select(*(changed[c].alias(c) if changed.get(c) is not None else F.col(at[c]).alias(c) for c in docs.columns))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Windows of tokens: one row per piece of a document."""
    return packing.pack_documents(docs, vocabulary("word_bpe_49k.json"), WINDOW, 1)


STAGES = [("language", language), ("quality", good), ("near_duplicates", distinct), ("passages", fresh), ("packing", packed)]

ORACLE_SQL = None  # no stage of it can be said in SQL; tests hold each against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
