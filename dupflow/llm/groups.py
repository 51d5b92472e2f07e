"""Links inside buckets by representatives, never by all pairs of a crowd.

Members of a bucket are compared with representatives in rounds.  In each round
the representatives have been compared with all others of the bucket and leave.
In a bucket of more than ``SMALL`` open members a member that is linked to a
representative leaves as well: its class is known, and its links to the other
members of that representative follow from the class.  Other members stay, with
twice as many representatives in the next round, until a bucket has one member
or none.  Buckets of up to ``SMALL`` members are compared in full.

Links that are missed so, between members that met different representatives,
are looked for by a last pass in which the blocks of a crowd meet: all pairs of
two blocks are compared inside one row, and no row is made for a pair.

So rows grow with the members, not with the square of a bucket, as long as a
crowd is alike; members alike to nobody meet the representatives that remain.
"""

from __future__ import annotations

import functools
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dupflow.llm.common import materialize
from dupflow.llm.components import components

#: Buckets of at most so many open members are compared in full.
SMALL = 8
#: Rounds end, if the last pass follows, when links to representatives take out a smaller share of the members than this.
WORTHWHILE = 0.02
#: Members of a crowd meet the others in blocks of about so many.
BLOCK = 64

Side = Callable[[str], Column]


def linked(members: DataFrame, plausible: Callable[[Side, Side], Column], verify: Callable[[DataFrame], DataFrame], deepen: Callable[[DataFrame], DataFrame] | None = None, after: int = 3, rank: str = "node", whole: tuple[DataFrame, Callable[[Side, Side], Column]] | None = None, rounds: int | None = None) -> DataFrame:
    """(a, b), a < b: verified links among the members of buckets.

    ``members`` has (bucket, node) and whatever columns ``plausible`` reads of
    two members, by name, to rule a pair out cheaply; ``verify`` keeps the true
    pairs of (a, b).  After round ``after`` the rows of crowded buckets are dealt
    anew by ``deepen``, which gives them finer buckets.  Representatives are the
    members whose buckets hold the most, as the text that others were copied
    from does, then by a hash of ``rank``.  With ``whole``, a table of (node, ...)
    and the exact test of two of its rows, a last pass compares all members of
    each crowd that ended in different connected sets, so that these sets are
    those of all pairs.  With ``rounds`` it ends after so many, and what is
    left is for the caller.  Repeated rows count once.
    """
    payload = [c for c in members.columns if c not in ("bucket", "node")]
    members = _open(members.dropDuplicates(["bucket", "node"]))
    weight = members.groupBy("node").agg(F.sum("size").alias("weight"))
    members = materialize(members.join(weight, "node"), "members")
    crowds = materialize(members.where(F.col("size") > SMALL), "crowds") if whole is not None else None
    payload.append("weight")
    found, number, k = [], 0, 1
    while number != rounds and not members.isEmpty():
        drawn = Window.partitionBy("bucket").orderBy(F.desc("weight"), F.xxhash64(F.lit(number), rank), "node")
        leaders = members.withColumn("place", F.row_number().over(drawn)).where(F.col("place") <= k).drop("place", "size")
        leaders = materialize(leaders.select(*[F.col(c).alias(f"{c}_r") for c in leaders.columns]), "representatives")
        ends = [F.least("node", "node_r").alias("a"), F.greatest("node", "node_r").alias("b")]
        met = members.join(leaders, F.col("bucket") == F.col("bucket_r"))
        likely = plausible(lambda c: F.col(c), lambda c: F.col(f"{c}_r")) & (F.col("node") != F.col("node_r"))
        links = materialize(verify(met.where(likely).select(*ends).distinct()).select("a", "b"), "links")
        found.append(links)
        # representatives leave, and so do the members of crowds that are linked to one
        led = leaders.select(F.col("bucket_r").alias("bucket"), F.col("node_r").alias("node"))
        joined = met.where((F.col("size") > SMALL) & likely).select("bucket", "node", *ends).join(links, ["a", "b"]).select("bucket", "node")
        rest = members.join(led.unionAll(joined).distinct(), ["bucket", "node"], "left_anti")
        number, k = number + 1, 2 * k
        if deepen is not None and number == after:
            finer = deepen(rest.where(F.col("size") > SMALL)).select("bucket", "node", *payload)
            rest = rest.where(F.col("size") <= SMALL).select("bucket", "node", *payload).unionAll(finer).dropDuplicates(["bucket", "node"])
        before, members = members.count(), _open(rest.select("bucket", "node", *payload))
        if crowds is not None and before - members.count() - leaders.count() < WORTHWHILE * before:
            few = members.where(F.col("size") <= SMALL)
            found.append(materialize(in_full(few, plausible, verify), "links"))
            break
    if not found:
        kind = members.schema["node"].dataType
        return members.select(F.lit(None).cast(kind).alias("a"), F.lit(None).cast(kind).alias("b")).limit(0)
    links = functools.reduce(DataFrame.unionAll, found).distinct()
    if crowds is None:
        return links
    links = materialize(links, "links")
    comps = components(links)
    sets = crowds.join(comps, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    several = sets.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where(F.col("lo") != F.col("hi")).select("bucket")
    sets = materialize(sets.join(several, "bucket"), "crowds")
    if sets.isEmpty():
        return links
    return links.unionAll(between_sets(sets, payload, plausible, *whole)).distinct()


def in_full(members: DataFrame, plausible: Callable[[Side, Side], Column], verify: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(a, b): all links inside the buckets."""
    other = members.select(*[F.col(c).alias(f"{c}_r") for c in members.columns])
    pairs = members.join(other, (F.col("bucket") == F.col("bucket_r")) & (F.col("node") < F.col("node_r")) & plausible(lambda c: F.col(c), lambda c: F.col(f"{c}_r")))
    return verify(pairs.select(F.col("node").alias("a"), F.col("node_r").alias("b")).distinct()).select("a", "b")


def between_sets(sets: DataFrame, payload: list[str], plausible: Callable[[Side, Side], Column], own: DataFrame, near: Callable[[Side, Side], Column]) -> DataFrame:
    """(a, b): of any two sets ``comp`` with a link inside a bucket one such link at least.

    ``sets`` has (bucket, size, node, comp) and the columns that ``plausible``
    reads, ``own`` those that ``near`` reads.  A pair is compared in the first
    bucket that it shares.
    """
    buckets = sets.groupBy("node").agg(F.sort_array(F.collect_set("bucket")).alias("buckets"))
    about = [c for c in own.columns if c != "node"]
    members = sets.join(buckets, "node").join(own, "node").withColumn("blocks", F.ceil(F.col("size") / BLOCK).cast("int"))
    members = members.withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    blocks = members.groupBy("bucket", "blocks", "block").agg(F.collect_list(F.struct("node", "comp", "buckets", *payload, *about)).alias("ours"))
    blocks = materialize(blocks, "crowd-blocks")
    others = blocks.select("bucket", F.col("block").alias("other"), F.col("ours").alias("theirs"))
    met = blocks.withColumn("other", F.explode(F.sequence(F.col("block"), F.col("blocks") - 1))).join(others, ["bucket", "other"])

    def linked_to(x: Column) -> Column:
        def same(y: Column) -> Column:
            here = (x["comp"] != y["comp"]) & ((F.col("block") != F.col("other")) | (x["node"] < y["node"]))
            sides = (lambda c: x[c]), (lambda c: y[c])
            first = F.array_min(F.array_intersect(x["buckets"], y["buckets"])) == F.col("bucket")
            return here & plausible(*sides) & first & near(*sides)

        ends = F.transform(F.filter("theirs", same), lambda y: F.struct(F.least(x["node"], y["node"]).alias("a"), F.greatest(x["node"], y["node"]).alias("b"), F.least(x["comp"], y["comp"]).alias("c"), F.greatest(x["comp"], y["comp"]).alias("d")))
        # one link to each other set is enough
        return F.filter(ends, lambda e, i: F.array_position(F.transform(ends, lambda z: F.struct(z["c"], z["d"])), F.struct(e["c"], e["d"])) == i + 1)

    found = met.select(F.explode(F.flatten(F.transform("ours", linked_to))).alias("x"))
    return found.groupBy("x.c", "x.d").agg(F.min(F.struct("x.a", "x.b")).alias("x")).select("x.a", "x.b")


def _open(members: DataFrame) -> DataFrame:
    """The rows of buckets of two members or more, with their number."""
    size = members.groupBy("bucket").agg(F.count("*").alias("size")).where(F.col("size") > 1)
    return materialize(members.join(size, "bucket"), "members")
