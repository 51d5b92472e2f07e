"""Secret scan with corpus-wide ownership: whose is each candidate, and how many hold it?

Candidates of all documents are hashed and counted by distinct repositories and
owners.  A value under many owners is a copied example; one under a single
owner looks live.  Spans come from built-in expressions: the text is split by
the pattern, so the lengths of pieces and matches give the offsets.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dupflow.llm.common import materialize, text_or_empty

#: Kinds in their order, their patterns, and the least length of what counts.
KINDS = ["assign", "access", "hex", "owned"]
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ASSIGN_HINTS = ["password", "passwd", "secret", "token", "api"]
ACCESS = r"AKIA[A-Z0-9]{12,}"
HEX = r"[0-9a-f]{32,}"
#: A value is a widely copied example only if more owners and repositories than these hold it, or more repositories of any owners than the last.
MAX_OWNERS, MAX_REPOSITORIES, HOT_REPOSITORIES = 3, 10, 1000
#: The method's own candidates: long key-like runs with digits and letters.
KEYLIKE = r"[A-Za-z0-9+/_=-]{20,}"

SPAN = "array<struct<start:int,rank:int,end:int,kind:string,value:string>>"
NONE = f"cast(array() as {SPAN})"


def spans(text: Column, pattern: str, rank: int, group: int = 0) -> Column:
    """Leftmost non-overlapping matches with code-point offsets, end exclusive."""
    pieces, hits = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    values = hits if not group else F.regexp_extract_all(text, F.lit(pattern), F.lit(group))
    both = F.arrays_zip(F.slice(pieces, F.lit(1), F.size(hits)).alias("gap"), hits.alias("hit"), values.alias("value"))
    start = F.struct(F.lit(0).alias("at"), F.expr(NONE).alias("found"))

    def step(acc: Column, x: Column) -> Column:
        a = acc["at"] + F.length(x["gap"])
        b = a + F.length(x["hit"])
        one = F.struct(a.alias("start"), F.lit(rank).alias("rank"), b.alias("end"), F.lit(KINDS[rank]).alias("kind"), x["value"].alias("value"))
        return F.struct(b.alias("at"), F.concat(acc["found"], F.array(one)).alias("found"))

    return F.aggregate(both, start, step, lambda acc: acc["found"])


def base_spans(text: Column) -> list[Column]:
    """The spans of the three base kinds; cheap tests keep most texts from the patterns."""
    low = F.lower(text)
    hinted = (text.contains("=") | text.contains(":")) & F.array_contains(F.array(*[low.contains(h) for h in ASSIGN_HINTS]), True)
    none = F.expr(NONE)
    return [
        F.when(hinted, F.filter(spans(text, ASSIGN, 0, 1), lambda s: F.length(s["value"]) >= 8)).otherwise(none),
        F.when(text.contains("AKIA"), spans(text, ACCESS, 1)).otherwise(none),
        F.when(text.rlike(HEX), spans(text, HEX, 2)).otherwise(none),
    ]


def keylike_spans(text: Column) -> Column:
    """Candidates beyond the base kinds: key-like runs that mix letters and digits."""
    mixed = lambda s: s["value"].rlike("[0-9]") & s["value"].rlike("[A-Za-z]")
    return F.when(text.rlike(KEYLIKE), F.filter(spans(text, KEYLIKE, 3), mixed)).otherwise(F.expr(NONE))


def ownership(candidates: DataFrame) -> DataFrame:
    """Rows (hash, owner, repository) to one row for each hash: distinct repositories and owners.

    Distinct first by the full key, so a value that a third of all rows hold
    is spread over tasks; each later step sums partial counts.
    """
    each = candidates.distinct()
    by_owner = each.groupBy("hash", "owner").agg(F.count("*").alias("repositories"))
    return by_owner.groupBy("hash").agg(F.sum("repositories").alias("n_repositories"), F.count("*").alias("n_owners"))


def scan(docs: DataFrame, repository: str = "doc_id", owner: str = "source", max_owners: int = MAX_OWNERS, max_repositories: int = MAX_REPOSITORIES, hot_repositories: int = HOT_REPOSITORIES) -> DataFrame:
    """One row for each document with all spans and the verdict on each.

    A candidate is a copied example if it is held by more than ``max_owners``
    distinct owners and more than ``max_repositories`` distinct repositories,
    or, whoever owns them, by more than ``hot_repositories``;
    any other is live.  Base spans stay whatever the verdict;
    a key-like candidate outside base spans becomes an ``owned`` span only if
    live.  Null texts are empty and texts of any length are read whole; null
    owners and repositories count as one value each.  Rows are told apart by id
    and text: equal rows give equal rows; an empty table gives none.
    """
    t = text_or_empty()
    found = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.xxhash64(t).alias("rid"),
        F.col(f"`{repository}`").cast("string").alias("repository"),
        F.col(f"`{owner}`").cast("string").alias("owner"),
        *[c.alias(k) for c, k in zip([*base_spans(t), keylike_spans(t)], KINDS, strict=True)],
    )
    found = found.withColumn("base", F.concat("assign", "access", "hex"))
    outside = lambda s: ~F.exists("base", lambda b: (b["start"] < s["end"]) & (s["start"] < b["end"]))
    found = found.withColumn("all", F.concat("base", F.filter("owned", outside)))
    found = found.select("doc_id", "rid", "repository", "owner", "assign", "access", "hex", "base", "all", F.transform("all", lambda s: F.xxhash64(s["value"])).alias("hashes"))
    found = materialize(found, "secret-spans")
    holders = found.where(F.size("all") > 0)
    rows = holders.select("doc_id", "rid", "repository", "owner", F.explode(F.array_distinct("hashes")).alias("hash"))
    counts = ownership(rows.select("hash", "owner", "repository"))
    verdicts = rows.select("doc_id", "rid", "hash").distinct().join(counts, "hash")
    of_doc = verdicts.groupBy("doc_id", "rid").agg(F.map_from_entries(F.collect_list(F.struct("hash", F.struct("n_owners", "n_repositories")))).alias("held"))  # a text's own candidates
    joined = found.join(of_doc, found["doc_id"].eqNullSafe(of_doc["doc_id"]) & (found["rid"] == of_doc["rid"]), "left").select(found["*"], "held")
    n = lambda s, count: F.col("held")[F.xxhash64(s["value"])][count]

    def is_live(s: Column) -> Column:
        few = (n(s, "n_owners") <= max_owners) | (n(s, "n_repositories") <= max_repositories)
        return few & (n(s, "n_repositories") <= hot_repositories)

    live = F.filter("all", is_live)
    return joined.select(
        "doc_id", "rid", "assign", "access", "hex", "base", "all", "held", live.alias("live"),
        F.filter("all", lambda s: (s["rank"] < 3) | is_live(s)).alias("kept"),
    )


def _written(c: Column) -> Column:
    return F.array_join(F.transform(F.sort_array(c), lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan_digest(docs: DataFrame, **how) -> DataFrame:
    """The digest columns of :func:`scan`, with the most owners and repositories that hold one of a document's candidates."""
    s = scan(docs, **how)
    most = lambda c: F.coalesce(F.array_max(F.transform(F.map_values("held"), lambda x: x[c])), F.lit(0)).cast("long")
    count = lambda c: F.size(c).cast("long")
    return s.select(
        "doc_id", count("assign").alias("n_assign"), count("access").alias("n_access"), count("hex").alias("n_hex"),
        F.sha2(_written(F.col("base")).cast("binary"), 256).alias("base_sha256"), _written(F.col("kept")).alias("spans"),
        F.coalesce(count("live"), F.lit(0)).alias("n_live"), (count("all") - count("live")).alias("n_copied"),
        most("n_owners").alias("most_owners"), most("n_repositories").alias("most_repositories"),
    )


def redact(docs: DataFrame, mark: str = "[SECRET]", **how) -> DataFrame:
    """All documents, with the values of live spans replaced by ``mark``; n_chars is renewed, other columns stay.

    Copied examples are left alone.  Rows are matched by id and text, so rows
    with equal ids are redacted each by its own text.
    """
    live = scan(docs, **how).where(F.size("live") > 0).dropDuplicates(["doc_id", "rid"])
    live = live.select(F.col("doc_id").alias("__id"), F.col("rid").alias("__rid"), F.sort_array(F.transform("live", lambda s: F.struct((s["end"] - F.length(s["value"])).alias("start"), s["end"].alias("end")))).alias("__live"))
    text = F.col("text")

    def step(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        out = F.when(fresh, F.concat(acc["out"], F.substr(text, acc["at"] + 1, s["start"] - acc["at"]), F.lit(mark))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), out.alias("out"))

    joined = docs.join(live, docs["doc_id"].eqNullSafe(live["__id"]) & (F.xxhash64(text_or_empty()) == live["__rid"]), "left")
    clean = F.aggregate("__live", F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step, lambda acc: F.concat(acc["out"], F.substr(text, acc["at"] + 1)))
    new = {c: docs[c] for c in docs.columns} | {"text": F.coalesce(clean, text).alias("text")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("__live").isNull(), F.col("n_chars")).otherwise(F.length(clean).cast("long")).alias("n_chars")
    return joined.select(*new.values())
