"""Bounded, balanced samples of labelled rows; the split into rows that may teach and rows held out."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def held_out(doc_id: Column) -> Column:
    """crc32 of the identifier as text leaves 2 when divided by 4; a null identifier is not held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def sample(docs: DataFrame, labels: DataFrame, label: str, per_class: int) -> DataFrame:
    """doc_id, text, label of at most per_class documents of label 0 and of label 1, none of them held out.

    Which ones depends on a hash of the identifier alone. Documents with no or an unclear label are left out.
    """
    graded = labels.filter(F.col("doc_id").isNotNull() & F.col(label).isNotNull()).groupBy(F.col("doc_id").cast("long").alias("_id")).agg(F.min(label).alias("label"), F.max(label).alias("_most"))
    usable = graded.filter((F.col("label") == F.col("_most")) & ~held_out(F.col("_id")))
    order = F.xxhash64("_id", F.lit(11))
    picked = None
    for c in (0, 1):
        part = usable.filter(F.col("label") == c).select("_id", F.lit(c).alias("label")).orderBy(order, "_id").limit(per_class)
        picked = part if picked is None else picked.union(part)
    once = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text"))
    # At most 2 * per_class identifiers: a bound that no input moves.
    return once.join(F.broadcast(picked), once.doc_id == picked._id).select("doc_id", F.coalesce("text", F.lit("")).alias("text"), "label")
