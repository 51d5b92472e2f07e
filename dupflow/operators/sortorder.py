"""Coordinate order as a by-product of the range-partitioned index."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dupflow import schema as S
from dupflow.plans.pool import pool

LAST_REF = 2147483647


def ref_order() -> Column:
    """Unmapped records go last."""
    return F.when(F.col("ref_id") < 0, F.lit(LAST_REF)).otherwise(F.col("ref_id"))


def sorted_scan(records: DataFrame, partitions: int | None = None) -> DataFrame:
    """All records in (reference, position, seq) order: one range shuffle, then a sort inside each part.

    seq is in the range key, so a pile-up or the unmapped tail spreads over parts.
    """
    keyed = records.withColumn("__ref", ref_order())
    n = [partitions] if partitions else []
    return keyed.repartitionByRange(*n, "__ref", "pos", "seq").sortWithinPartitions("__ref", "pos", "seq").drop("__ref")


def sort_by_name(records: DataFrame) -> DataFrame:
    return records.repartitionByRange("qname", "seq").sortWithinPartitions("qname", "seq")


def overlay_sorted(records: DataFrame, marks: DataFrame) -> DataFrame:
    """Marks and order in one shuffle of the full records.

    Mark rows carry the sort key of the record they mark and ride along; after
    the range partition the window over that key needs no second exchange.
    Marks are written first: the range partition samples its input, which would
    otherwise run the whole marking twice.  ``records`` should be pooled for
    the same reason.
    """
    marks = pool(marks.select("seq", "ref_id", "pos"), "storage")
    nothing = [F.lit(None).cast(records.schema[c].dataType).alias(c) for c in records.columns if c not in ("seq", "ref_id", "pos")]
    riders = marks.select("seq", F.col("ref_id").cast("int").alias("ref_id"), "pos", *nothing).select(*records.columns)
    both = records.withColumn("__mark", F.lit(0)).unionByName(riders.withColumn("__mark", F.lit(1))).withColumn("__ref", ref_order())
    parts = both.repartitionByRange("__ref", "pos", "seq")
    w = Window.partitionBy("__ref", "pos", "seq").orderBy(F.desc("__mark")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    hit = parts.withColumn("__hit", F.max("__mark").over(w)).where("__mark = 0")
    clear = F.col("flag").bitwiseAND(F.lit(~S.DUPLICATE))
    return hit.withColumn("flag", F.when(F.col("__hit") == 1, clear.bitwiseOR(F.lit(S.DUPLICATE))).otherwise(clear)).select(*records.columns)
