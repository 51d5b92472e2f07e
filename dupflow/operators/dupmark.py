"""Duplicate marking.

Pairs with the same two ends (reference, unclipped 5' coordinate, strand, in
either order) compete; the best score stays.  A fragment, an end whose mate is
not mapped, is a duplicate wherever a pair has an end; among lone fragments the
best stays.  Ties go to the place in the sorted file, then to the input order.
The score threshold, the exemptions and the fragment rule are public
convention, as is everything about libraries.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dupflow import schema as S
from dupflow.plans.pool import pool

END = ["ref_id", "u5", "rev"]
PAIR_KEY = ["klib", "ra", "ua", "va", "rb", "ub", "vb"]
FRAGMENT_KEY = ["klib", "ref_id", "u5", "rev"]


def eligible(digests: DataFrame) -> DataFrame:
    """Mapped primary ends; unmapped, secondary and supplementary records never take part."""
    return digests.where(F.col("flag").bitwiseAND(F.lit(S.UNMAPPED | S.SECONDARY | S.SUPPLEMENTARY)) == 0)


def collapse(digests: DataFrame, by_library: bool = False, coarse: int = 1) -> DataFrame:
    """One row for each template: both ends side by side, null where an end is not mapped.

    One shuffle of digests.  All aggregates are single numbers, so it is a hash
    aggregate with a map-side part.
    """
    d = eligible(digests)
    one = lambda c, e: F.max(F.when(F.col("end_no") == e, F.col(c))).alias(f"{c}{e}")
    t = d.groupBy("tid").agg(F.max("lib").alias("lib"), *[one(c, e) for e in (1, 2) for c in ("ref_id", "u5", "rev", "pos", "score", "seq")])
    return t.withColumn("klib", F.col("lib") if by_library else F.lit("")).withColumn("coarse", F.lit(coarse))


def pairs(templates: DataFrame) -> DataFrame:
    """Templates with both ends, the end with the smaller (reference, coordinate, strand, end number) first."""
    both = templates.where(F.col("ref_id1").isNotNull() & F.col("ref_id2").isNotNull())
    first = F.struct("ref_id1", "u51", "rev1") <= F.struct(F.col("ref_id2").alias("ref_id1"), F.col("u52").alias("u51"), F.col("rev2").alias("rev1"))
    pick = lambda c, a: F.when(first, F.col(f"{c}{1 if a else 2}")).otherwise(F.col(f"{c}{2 if a else 1}"))
    score = F.col("score1") + F.col("score2")
    return both.select(
        "tid", "klib", pick("ref_id", True).alias("ra"), pick("u5", True).alias("ua"), pick("rev", True).alias("va"), pick("ref_id", False).alias("rb"), pick("u5", False).alias("ub"), pick("rev", False).alias("vb"),
        pick("pos", True).alias("pos"), F.floor(score / F.col("coarse")).cast("long").alias("score"), pick("seq", True).alias("sa"), pick("seq", False).alias("sb"), pick("pos", False).alias("pos_b"), F.least("seq1", "seq2").alias("first_seq"),
    )


def fragments(templates: DataFrame) -> DataFrame:
    """Templates with one mapped end."""
    alone = templates.where(F.col("ref_id1").isNull() | F.col("ref_id2").isNull())
    it = lambda c: F.coalesce(f"{c}1", f"{c}2").alias(c)
    return alone.select("tid", "klib", it("ref_id"), it("u5"), it("rev"), it("pos"), F.floor(F.coalesce("score1", "score2") / F.col("coarse")).cast("long").alias("score"), it("seq"), F.coalesce("seq1", "seq2").alias("first_seq"))


def rank_of(tie: str = "sorted") -> Column:
    """Least is best: higher score, then (sorted) the place in the sorted file, then the input order."""
    return F.struct((-F.col("score")).alias("neg"), *([F.col("pos")] if tie == "sorted" else []), F.col("first_seq"), F.col("tid"))


def _losers_agg(rows: DataFrame, key: list[str], tie: str) -> DataFrame:
    """Rows that are not their key's best, with the best's template and the size of the set.

    The best of a key is a partial and final aggregate, so electing it needs one
    row of memory however many rows a key has.  Rows then meet their key's best
    by a join, where a hot key is left to the engine's split of skewed parts.
    """
    best = rows.groupBy(*key).agg(F.min(rank_of(tie))["tid"].alias("rep"), F.count("*").alias("set_size")).where(F.col("set_size") > 1)
    return rows.join(best, key).where(F.col("tid") != F.col("rep"))


def _losers_window(rows: DataFrame, key: list[str], tie: str) -> DataFrame:
    order = Window.partitionBy(*key).orderBy(rank_of(tie))
    whole = Window.partitionBy(*key)
    return rows.withColumn("rep", F.first("tid").over(order)).withColumn("set_size", F.count("*").over(whole)).withColumn("rn", F.row_number().over(order)).where("rn > 1").drop("rn")


def mark_pairs(templates: DataFrame, how: str = "agg", tie: str = "sorted") -> DataFrame:
    """Duplicate pairs by the aggregate (``agg``) or the window (``window``) plan."""
    return (_losers_agg if how == "agg" else _losers_window)(pairs(templates), PAIR_KEY, tie)


def pair_ends(p: DataFrame, beside: DataFrame | None = None) -> DataFrame:
    """Distinct places that pair ends occupy, of those in the sieve ``beside`` if there is one."""
    a = p.select("klib", F.col("ra").alias("ref_id"), F.col("ua").alias("u5"), F.col("va").alias("rev"))
    ends = a.unionAll(p.select("klib", "rb", "ub", "vb"))
    if beside is not None:
        ends = placed_in(ends, _sieve_place(*FRAGMENT_KEY), beside).where("__may").drop("__may")
    return ends.distinct()


def mark_fragments(templates: DataFrame, how: str = "agg", tie: str = "sorted", sift: bool = False) -> DataFrame:
    """Duplicate fragments: all at a pair end's place, else all but the best; rep is null beside a pair.

    With ``sift`` pair ends at places without a fragment are left out by a sieve
    before they are shuffled; ``templates`` should be stored then.
    """
    f = fragments(templates)
    sized = f.groupBy(*FRAGMENT_KEY).agg(F.min(rank_of(tie))["tid"].alias("rep"), F.count("*").alias("set_size"))
    beside = sieve(_sieve_place(*FRAGMENT_KEY), f.select(*FRAGMENT_KEY)) if sift else None
    places = pair_ends(pairs(templates), beside).withColumn("hit", F.lit(True))
    keys = sized.join(places, FRAGMENT_KEY, "left")
    marked = f.join(keys, FRAGMENT_KEY).where(F.coalesce("hit", F.lit(False)) | (F.col("tid") != F.col("rep")))
    if how == "window":
        lost = _losers_window(f, FRAGMENT_KEY, tie).select(*f.columns, "rep", "set_size")
        at = f.join(places, FRAGMENT_KEY).withColumn("set_size", F.count("*").over(Window.partitionBy(*FRAGMENT_KEY)))
        marked = at.select(*f.columns, F.lit(None).cast(f.schema["tid"].dataType).alias("rep"), "set_size").unionByName(lost.join(places, FRAGMENT_KEY, "left_anti").select(*f.columns, "rep", "set_size")).withColumn("hit", F.col("rep").isNull())
    return marked.withColumn("rep", F.when(~F.coalesce("hit", F.lit(False)), F.col("rep"))).drop("hit")


def mark_templates(digests: DataFrame, how: str = "agg", tie: str = "sorted", by_library: bool = False, coarse: int = 1) -> DataFrame:
    """(tid, kind, rep, set_size) of every duplicate template."""
    t = collapse(digests, by_library, coarse)
    p = mark_pairs(t, how, tie).select("tid", F.lit("pair").alias("kind"), "rep", "set_size")
    return p.unionAll(mark_fragments(t, how, tie).select("tid", F.lit("fragment").alias("kind"), "rep", "set_size"))


def mark_records(digests: DataFrame, **how) -> DataFrame:
    """(seq, ref_id, pos) of every marked record: both ends of pairs, the mapped end of fragments.

    Templates are written first, as several branches read them, each with its
    own columns, and would otherwise shuffle all digests again.  Pairs whose key
    nobody shares are told by a sieve of key hashes; only the others are
    shuffled to elect the best, which compares the keys themselves.
    """
    t = pool(collapse(digests, how.get("by_library", False), how.get("coarse", 1)).drop("lib"), "storage")
    p = (_losers_agg if how.get("how", "agg") == "agg" else _losers_window)(shared_keys(pairs(t), PAIR_KEY), PAIR_KEY, how.get("tie", "sorted"))
    f = mark_fragments(t, how.get("how", "agg"), how.get("tie", "sorted"), sift=True)
    ends = F.array(F.struct(F.col("sa").alias("seq"), F.col("ra").alias("ref_id"), F.col("pos").alias("pos")), F.struct(F.col("sb").alias("seq"), F.col("rb").alias("ref_id"), F.col("pos_b").alias("pos")))
    return p.select(F.inline(ends)).unionAll(f.select("seq", "ref_id", "pos"))


#: Bits of a sieve that tells most rows apart before a shuffle, and bytes of one of its pieces.
SIEVE_BITS, PIECE_BYTES = 1 << 26, 4096


def _sieve_place(*key: str) -> Column:
    """Place of a row in a sieve by a key of one or more columns, from 1."""
    return F.pmod(F.xxhash64(*key), F.lit(SIEVE_BITS)) + 1


def sieve(places: Column, rows: DataFrame) -> DataFrame:
    """A bit for each place of ``rows``, 8 MB in all however many rows there are."""
    return rows.groupBy(F.bitmap_bucket_number(places).alias("__piece")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(places)).alias("__bits"))


def placed_in(rows: DataFrame, places: Column, bits: DataFrame) -> DataFrame:
    """``rows`` with __may, true where the bit of their place is set in the sieve ``bits``, which goes to every task."""
    byte = F.conv(F.hex(F.substring("__bits", (F.shiftright("__bit", 3) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    may = F.coalesce(F.call_function("getbit", byte.cast("long"), F.col("__bit").bitwiseAND(F.lit(7)).cast("int")) == 1, F.lit(False))
    met = rows.withColumn("__piece", F.bitmap_bucket_number(places)).withColumn("__bit", F.bitmap_bit_position(places)).join(F.broadcast(bits), "__piece", "left")
    return met.select(*rows.columns, may.alias("__may"))


def shared_keys(rows: DataFrame, key: list[str]) -> DataFrame:
    """``rows`` without most of those whose key no other row has; none that shares its key is left out.

    Counts of key hashes are shuffled, not rows.
    """
    often = rows.groupBy(F.xxhash64(*key).alias("__hash")).agg(F.count("*").alias("__n")).where("__n > 1")
    bits = sieve(F.pmod(F.col("__hash"), F.lit(SIEVE_BITS)) + 1, often)
    return placed_in(rows, _sieve_place(*key), bits).where("__may").drop("__may")


def apply_marks(records: DataFrame, marks: DataFrame) -> DataFrame:
    """Sets the duplicate bit of marked records and clears it from all others, by a join on seq.

    Marks are written first, and a bit for each of them goes to every task, 8 MB
    in all.  Records whose bit is not set are unmarked and stay where they are;
    only the others, the marked ones and those that share a bit with one, are
    shuffled for the join, which decides.
    """
    marks = pool(marks.select("seq"), "storage")
    placed = placed_in(records, _sieve_place("seq"), sieve(_sieve_place("seq"), marks))
    clear = F.col("flag").bitwiseAND(F.lit(~S.DUPLICATE))
    hit = marks.withColumn("hit", F.lit(True))
    met = placed.where("__may").select(*records.columns).join(hit, "seq", "left")
    met = met.withColumn("flag", F.when(F.col("hit"), clear.bitwiseOR(F.lit(S.DUPLICATE))).otherwise(clear)).select(*records.columns)
    return placed.where("not __may").select(*records.columns).withColumn("flag", clear).select(*records.columns).unionAll(met)


def tie_sets(templates: DataFrame) -> DataFrame:
    """Pair keys with more than one best score: (key, n_best, set_size)."""
    p = pairs(templates)
    best = p.groupBy(*PAIR_KEY).agg(F.max("score").alias("best"), F.count("*").alias("set_size"))
    same = p.join(best, PAIR_KEY).where(F.col("score") == F.col("best"))
    return same.groupBy(*PAIR_KEY, "set_size").agg(F.count("*").alias("n_best")).where("n_best > 1")


def mark_keyed(df: DataFrame, key: list[str], score: Column, tie: Column, salt: int = 0) -> DataFrame:
    """Marking for any table: all rows of a key but its best are duplicates.

    Adds is_dup and rep_tie.  With ``salt`` the best is taken in two levels,
    first within that many shares of each key.
    """
    rank = F.struct((-score).alias("neg"), tie.alias("tie"))
    keyed = df.withColumn("__rank", rank)
    if salt:
        part = keyed.groupBy(*key, F.pmod(F.xxhash64("__rank"), F.lit(salt)).alias("__salt")).agg(F.min("__rank").alias("__best"), F.count("*").alias("__n"))
        best = part.groupBy(*key).agg(F.min("__best").alias("__best"), F.sum("__n").alias("set_size"))
    else:
        best = keyed.groupBy(*key).agg(F.min("__rank").alias("__best"), F.count("*").alias("set_size"))
    best = best.select(*[F.col(k).alias(f"__k{i}") for i, k in enumerate(key)], "__best", "set_size")
    cond = F.lit(True)
    for i, k in enumerate(key):
        cond = cond & F.col(k).eqNullSafe(F.col(f"__k{i}"))
    joined = keyed.join(best, cond)
    return joined.select(*df.columns, (F.col("__rank") != F.col("__best")).alias("is_dup"), F.col("__best")["tie"].alias("rep_tie"), "set_size")


def brute_mark(digests: DataFrame) -> DataFrame:
    """Duplicate pairs by comparing every two pairs; for tests on small inputs only."""
    p = pairs(collapse(digests))
    other = p.select(*[F.col(c).alias(f"o_{c}") for c in p.columns])
    same = None
    for k in PAIR_KEY:
        c = F.col(k) == F.col(f"o_{k}")
        same = c if same is None else same & c
    better = F.struct(-F.col("o_score"), F.col("o_pos"), F.col("o_first_seq")) < F.struct(-F.col("score"), F.col("pos"), F.col("first_seq"))
    return p.join(other, same & better, "left_semi").select("tid")
