"""Digest: the narrow summary of each record that analyzers work on."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dupflow import schema as S
from dupflow.functions.geometry import has, quality_score, reverse, unclipped_5p


def record_bytes() -> Column:
    """Size of a record in the block format, from the lengths of its parts."""
    return (F.lit(44) + F.length("qname") + 4 * F.size(F.regexp_extract_all("cigar", F.lit(r"([0-9]+)"), F.lit(1))) + 2 * F.length("bases") + F.aggregate("tags", F.lit(0), lambda a, t: a + 3 + F.length(t["value"]))).cast("long")


def digest(records: DataFrame, extras: dict[str, Column] | None = None) -> DataFrame:
    """Narrow rows; ``extras`` are the plug-ins' own summaries of long parts that are not kept."""
    f = F.col("flag")
    made = {
        "seq": F.col("seq"), "tid": F.col("tid"), "end_no": F.when(has(f, S.END1), 1).otherwise(2), "flag": f, "ref_id": F.col("ref_id"), "pos": F.col("pos"),
        "u5": F.when(has(f, S.UNMAPPED), F.lit(0).cast("long")).otherwise(unclipped_5p(F.col("pos"), F.col("cigar"), f)), "rev": reverse(f), "score": quality_score(F.col("quals")), "lib": F.col("lib"), "rec_bytes": record_bytes(),
    }
    return records.select(*[c.alias(n) for n, c in (made | (extras or {})).items()])
