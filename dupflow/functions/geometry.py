"""Mapping geometry as expressions: clips, reference span, unclipped 5' coordinate."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from dupflow import schema as S


def _sum(numbers: Column) -> Column:
    return F.aggregate(numbers, F.lit(0).cast("long"), lambda a, x: a + x.cast("long"))


def leading_clip(cigar: Column) -> Column:
    """Bases clipped before the first mapped one, hard and soft."""
    return _sum(F.regexp_extract_all(F.regexp_extract(cigar, r"^((?:[0-9]+[HS])+)", 1), F.lit(r"([0-9]+)"), F.lit(1)))


def trailing_clip(cigar: Column) -> Column:
    return _sum(F.regexp_extract_all(F.regexp_extract(cigar, r"[^HS0-9]((?:[0-9]+[HS])+)$", 1), F.lit(r"([0-9]+)"), F.lit(1)))


def span(cigar: Column) -> Column:
    """Reference bases covered: operations M, D, N, = and X."""
    return _sum(F.regexp_extract_all(cigar, F.lit(r"([0-9]+)[MDN=X]"), F.lit(1)))


def has(flag: Column, bit: int) -> Column:
    return flag.bitwiseAND(F.lit(bit)) != 0


def reverse(flag: Column) -> Column:
    return F.when(has(flag, S.REVERSE), 1).otherwise(0)


def unclipped_5p(pos: Column, cigar: Column, flag: Column) -> Column:
    """Forward: start less leading clips; reverse: end plus trailing clips."""
    return F.when(has(flag, S.REVERSE), pos + span(cigar) - 1 + trailing_clip(cigar)).otherwise(pos - leading_clip(cigar))


def overlaps(ref: Column, pos: Column, cigar: Column, want_ref, start, end) -> Column:
    """Whether any covered reference base lies in the interval, ends included."""
    return (ref == want_ref) & (pos <= end) & (pos + F.greatest(span(cigar), F.lit(1)) - 1 >= start)


def cigar_ops(cigar: Column) -> Column:
    """Array of (op, len)."""
    return F.transform(F.regexp_extract_all(cigar, F.lit(r"([0-9]+[MIDNSHP=X])"), F.lit(1)), lambda x: F.struct(F.substr(x, F.length(x), F.lit(1)).alias("op"), F.substr(x, F.lit(1), F.length(x) - 1).cast("int").alias("len")))


def quality_score(quals: Column, min_q: int = 15) -> Column:
    """Sum of the base qualities of at least ``min_q``; the text holds quality + 33."""
    return F.aggregate(F.split(quals, ""), F.lit(0).cast("long"), lambda a, c: a + F.when(F.ascii(c) - 33 >= min_q, (F.ascii(c) - 33).cast("long")).otherwise(F.lit(0).cast("long")))
