"""Corpus pipeline: quality filter, exact and near deduplication, decontamination, tokenisation.

Each stage is (name, function); a function takes (spark, docs, sf_dir) and returns the documents it keeps with the
columns of documents, the last one the token digests. Stages are written as Parquet and read again, so a lost
executor never costs more than the running stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from halograph.llm.bpe import bpe_digests
from halograph.llm.common import Scratch
from halograph.llm.decontaminate import decontaminate
from halograph.llm.exact_dedup import exact_dedup
from halograph.llm.near_dedup import near_dedup
from halograph.llm.quality import keep_good, train

#: SQL has no conditional random field, so the pipeline is tested against brute force instead.
ORACLE_SQL = None
_stages: list[Scratch] = []


def _fresh(spark: SparkSession) -> Scratch:
    """Scratch of a stage. What earlier stages wrote for themselves goes, for their results have been written and read
    again by then; tables of operators that others called stay."""
    while _stages:
        _stages.pop().drop()
    _stages.append(Scratch(spark))
    return _stages[-1]


def _numbered(docs: DataFrame, scratch: Scratch, nulls_last: bool) -> tuple[DataFrame, str]:
    """The rows with a number of their own, and the name of its column: doc_id where every row has one of its own, else
    numbers that rise with doc_id, written once. So verdicts hit the rows that were judged, also those without doc_id."""
    name = "row"
    while name in (c.lower() for c in docs.columns):
        name += "_"
    doc_id = F.col("doc_id").cast("long")
    if docs.groupBy(doc_id.alias("doc_id")).count().filter("count > 1 OR doc_id IS NULL").isEmpty():
        return docs.withColumn(name, doc_id), name
    order = doc_id.asc_nulls_last() if nulls_last else doc_id.asc_nulls_first()
    return scratch.keep(docs.orderBy(order).withColumn(name, F.monotonically_increasing_id()), "numbered"), name


def _only(rows: DataFrame, name: str, verdicts: DataFrame) -> DataFrame:
    kept = verdicts.filter("kept").select(F.col("doc_id").alias(name + "_kept"))
    return rows.join(kept, rows[name] == kept[name + "_kept"], "left_semi").drop(name)


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the line model finds good; it learns from labelled documents that are not held out. Rows are judged
    one by one by their text: null and empty texts, repeated rows and rows without doc_id too."""
    return keep_good(docs, train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of rows with equal texts (null equals empty) the one with the largest doc_id; rows without doc_id come last, and of
    rows that share a doc_id, or have none, any one stays. Other columns are carried along, whatever their names."""
    scratch = _fresh(spark)
    rows, name = _numbered(docs, scratch, nulls_last=False)
    return _only(rows, name, exact_dedup(rows.select(F.col(name).alias("doc_id"), "text"), keep="largest", scratch=scratch))


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates the row with the smallest doc_id; rows without doc_id stay only where the group has
    no other. Texts without words are in no group and stay."""
    scratch = _fresh(spark)
    rows, name = _numbered(docs, scratch, nulls_last=True)
    return _only(rows, name, near_dedup(rows.select(F.col(name).alias("doc_id"), "text"), scratch=scratch))


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text holds no benchmark item, each judged where it lies."""
    _fresh(spark)
    return decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str, ranks: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every row left."""
    import public_tokenizers

    _fresh(spark)
    return bpe_digests(docs, ranks or public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))


STAGES = [
    ("quality classifier", quality_stage),
    ("exact dedup", exact_stage),
    ("near dedup", near_stage),
    ("benchmark decontamination", benchmark_stage),
    ("byte-level bpe", token_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of sf_dir; an empty table goes through with no row at the end."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    written = Scratch(spark)
    for k, (_, stage) in enumerate(STAGES):
        docs = written.keep(stage(spark, docs, sf_dir), f"stage{k}")
    return docs
