"""Comparison of two marked outputs: extract, normalise, difference, verdict."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dupflow import schema as S


def extract_marked(records: DataFrame) -> DataFrame:
    return records.where(F.col("flag").bitwiseAND(F.lit(S.DUPLICATE)) != 0)


def sort_tags(records: DataFrame) -> DataFrame:
    """Optional fields in the order of their names."""
    return records.withColumn("tags", F.array_sort("tags"))


def tag_names(records: DataFrame) -> DataFrame:
    return records.select(F.explode("tags").alias("t")).select(F.col("t.tag").alias("tag")).distinct()


def common_tags(a: DataFrame, b: DataFrame) -> list[str]:
    """Names of optional fields in both outputs; two letters each, so a few thousand at most."""
    return sorted(r["tag"] for r in tag_names(a).intersect(tag_names(b)).collect())


def keep_tags(records: DataFrame, names: list[str]) -> DataFrame:
    return records.withColumn("tags", F.filter("tags", lambda t: t["tag"].isin(names)))


def without_version(header: DataFrame) -> DataFrame:
    """The header without its format version and program entries."""
    return header.where("kind <> 'PG'").withColumn("fields", F.map_filter("fields", lambda k, v: k != "VN"))


def normalise(a: DataFrame, b: DataFrame) -> tuple[DataFrame, DataFrame]:
    names = common_tags(a, b)
    return sort_tags(keep_tags(a, names)), sort_tags(keep_tags(b, names))


def as_text(records: DataFrame) -> DataFrame:
    """Normalised records as comparable rows; seq is no part of a record's content."""
    from dupflow.sources.taf import render_line

    return records.select(render_line().alias("line"))


def differences(a: DataFrame, b: DataFrame) -> DataFrame:
    """(only_a, only_b) counts of marked records, as multisets, after normalising both."""
    x, y = normalise(extract_marked(a), extract_marked(b))
    x, y = as_text(x), as_text(y)
    one = x.groupBy("line").agg(F.count("*").alias("n")).select("line", "n", F.lit(0).cast("long").alias("m")).unionAll(y.groupBy("line").agg(F.count("*").alias("m")).select("line", F.lit(0).cast("long"), "m"))
    each = one.groupBy("line").agg(F.sum("n").alias("n"), F.sum("m").alias("m"))
    return each.agg(F.coalesce(F.sum(F.greatest(F.col("n") - F.col("m"), F.lit(0))), F.lit(0)).cast("long").alias("only_a"), F.coalesce(F.sum(F.greatest(F.col("m") - F.col("n"), F.lit(0))), F.lit(0)).cast("long").alias("only_b"))


def verdict(a: DataFrame, b: DataFrame) -> DataFrame:
    return differences(a, b).withColumn("accurate", (F.col("only_a") == 0) & (F.col("only_b") == 0))
