"""Exact deduplication by a log-structured merge index over content digests (built-in functions only).

Rows fill memtables of bounded size in the order in which they are read. Each memtable is flushed as a run: one entry for
a digest, sorted by digest, in Parquet with a Bloom filter on the digest. Tiers of runs are compacted, FAN_IN runs to one,
until one level is left that keeps, for each digest, the identifier that stays and the number of rows; the filters let
``seen`` look up digests in a level without reading the row groups that cannot hold them. Verdicts go back to the rows
by run and digest, so the rows of a digest, however many, lie in as many places as there are runs. Documents that hit a
digest of several rows are then compared byte by byte with the text that stays; a digest shared by different texts is
split.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from halograph.llm.common import Scratch, ascii_lower

#: Rows of a memtable.
MEMTABLE_ROWS = 1 << 14
#: Runs of a tier that are compacted to one run of the next.
FAN_IN = 64
#: Rows of one group that are compared with one copy of the text that stays.
ROWS_PER_COPY = 512
_FILTER = {"parquet.bloom.filter.enabled#digest": "true", "parquet.bloom.filter.expected.ndv#digest": "200000"}


def sha256_digest(normalised: Column) -> Column:
    return F.sha2(normalised, 256)


def memtables(rows: DataFrame, memtable_rows: int = MEMTABLE_ROWS) -> DataFrame:
    """The rows with the number of their memtable: so many rows in a row of one input partition."""
    return rows.withColumn("run", F.call_function("div", F.monotonically_increasing_id(), F.lit(memtable_rows)))


def flush(keyed: DataFrame, scratch: Scratch) -> DataFrame:
    """Memtables to sorted runs: run, digest, least and most identifier, n."""
    entries = keyed.groupBy("run", "digest").agg(F.min("doc_id").alias("least"), F.max("doc_id").alias("most"), F.count(F.lit(1)).alias("n"))
    return scratch.keep(entries.sortWithinPartitions("run", "digest"), "runs", **_FILTER)


def compact(tier: DataFrame, scratch: Scratch, fan_in: int = FAN_IN) -> DataFrame:
    """Runs of a tier merged, ``fan_in`` to one, tier after tier until the last merge: the level, sorted by digest.

    Runs are numbered by input partition in the high and by order in the low bits; partitions are merged last.
    """
    last = tier.agg(F.countDistinct("run")).first()[0] or 0  # one number
    while last > fan_in:
        merged = tier.groupBy(F.pmod(F.xxhash64("run"), F.lit(-(-last // fan_in))).alias("run"), "digest").agg(*_merged())
        tier = scratch.keep(merged.sortWithinPartitions("run", "digest"), "tier", **_FILTER)
        last = -(-last // fan_in)
    return scratch.keep(tier.groupBy("digest").agg(*_merged()).sortWithinPartitions("digest"), "level", **_FILTER)


def _merged() -> list[Column]:
    return [F.min("least").alias("least"), F.max("most").alias("most"), F.sum("n").alias("n")]


def build_index(docs: DataFrame, scratch: Scratch, *, digest=sha256_digest, memtable_rows: int = MEMTABLE_ROWS, fan_in: int = FAN_IN) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(rows with run and digest, runs, level) of a table of documents."""
    text = F.coalesce(F.col("text"), F.lit(""))
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), digest(ascii_lower(text)).alias("digest"))
    keyed = scratch.keep(memtables(source, memtable_rows), "digests")
    runs = flush(keyed, scratch)
    return keyed, runs, compact(runs, scratch, fan_in)


def seen(level: DataFrame, digests: list[str]) -> DataFrame:
    """The entries of a few digests: the predicate reaches the scan, whose filters pass over most row groups."""
    return level.filter(F.col("digest").isin(digests))


def exact_dedup(docs: DataFrame, *, keep: str = "smallest", digest=sha256_digest, memtable_rows: int = MEMTABLE_ROWS, fan_in: int = FAN_IN, scratch: Scratch | None = None) -> DataFrame:
    """One row a document: doc_id, keep_id, group_size, kept, digest.

    Texts are equal when the same after lower-casing A-Z; a null text is empty, texts of any length are compared whole.
    ``keep`` says which identifier of equal texts stays. Repeated rows (same identifier and text) each count in
    group_size and share the verdict. A null doc_id never stays while its group has another; a group of null identifiers
    only has keep_id null and is not kept. Other columns of ``docs`` are not read. An empty table gives an empty result.
    """
    scratch = scratch or Scratch(docs.sparkSession)
    pick, stays = (F.min, "least") if keep == "smallest" else (F.max, "most")
    text = F.coalesce(F.col("text"), F.lit(""))
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    keyed, runs, level = build_index(docs, scratch, digest=digest, memtable_rows=memtable_rows, fan_in=fan_in)

    # The verdict of a digest goes to each run that has it, and from there to the rows of the run.
    told = runs.select("run", "digest").join(level.select("digest", F.col(stays).alias("stays"), "n"), "digest")
    judged = scratch.keep(keyed.join(told, ["run", "digest"]), "judged")
    alone = judged.filter("n = 1").select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), "digest")

    # The texts of hits are fetched by doc_id, which is spread evenly however large a group is.
    wanted = judged.filter("n > 1").select("doc_id", "digest", "stays", "n").distinct()
    fetched = scratch.keep(
        source.join(wanted, source.doc_id.eqNullSafe(wanted.doc_id))
        .select(source.doc_id, ascii_lower(F.col("text")).alias("body"), "digest", "stays", "n")
        .filter(digest(F.col("body")) == F.col("digest")),
        "hits",
    )
    copies = (F.col("n") / ROWS_PER_COPY).cast("long")
    part = F.pmod(F.xxhash64("doc_id", F.lit(7)), copies + 1)
    model = (
        fetched.filter(F.col("doc_id").eqNullSafe(F.col("stays")))
        .groupBy("digest", "n")
        .agg(F.min("body").alias("model"))
        .select("digest", "model", F.explode(F.sequence(F.lit(0).cast("long"), copies)).alias("part"))
    )
    compared = fetched.withColumn("part", part).join(model, ["digest", "part"]).select(
        "doc_id", "digest", "part", F.when(F.col("body") == F.col("model"), F.lit("")).otherwise(F.concat(F.lit("="), "body")).alias("other")
    )
    verified = scratch.keep(compared, "verified")
    groups = verified.groupBy("digest", "part", "other").agg(pick("doc_id").alias("best"), F.count(F.lit(1)).alias("rows"))
    whole = groups.groupBy("digest", "other").agg(pick("best").alias("keep_id"), F.sum("rows").alias("group_size"))
    parts = groups.select("digest", "part", "other").join(whole, ["digest", "other"])
    several = verified.join(parts, ["digest", "part", "other"]).select("doc_id", "keep_id", "group_size", "digest")
    return alone.unionByName(several).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("keep_id"), F.lit(False)))


def op7_exact_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = exact_dedup(docs, keep="largest")
    return out.select("doc_id", "keep_id", "group_size", "kept", F.col("digest").alias("text_sha256"))


OP7_SQL = """
WITH d AS (
  SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256
  FROM documents)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""
