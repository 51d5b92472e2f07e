"""Line-first cleaning: rules judge each line, failing lines go, and a document that loses too much goes too.

Everything is a built-in expression on one row; there is no shuffle.
"""

from __future__ import annotations

import functools

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dupflow.llm.common import text_or_empty

#: What a word is, and the symbols that are counted.
WORD = r"[^\x20\x09-\x0D]+"
SPACES = "\x20\x09\x0a\x0b\x0c\x0d"
SYMBOLS = "#*$%&|<>"

#: Lines with these phrases are boilerplate.
BOILERPLATE = r"(?i)lorem ipsum|enable javascript|use of cookies|cookie policy|accept cookies|privacy policy|terms of (use|service)|all rights reserved|licensed under|public license|sign up|log in|subscribe (now|to)|click here|read more|share this"
#: Lower-case parts, one of which is in whatever BOILERPLATE matches: they are looked for before the pattern is tried.
BOILERPLATE_PARTS = ("lorem ipsum", "enable javascript", "use of cookies", "cookie policy", "accept cookies", "privacy policy", "terms of ", "all rights reserved", "licensed under", "public license", "sign up", "log in", "subscribe ", "click here", "read more", "share this")
#: A line of prose ends in one of these, quotes and brackets aside.
SENTENCE_END = r"[.!?…。！？:;][\"'”’»)\]]*[\x20\x09-\x0D]*$"


def _count(text: Column, chars: str) -> Column:
    """Number of occurrences of the given single characters."""
    total = F.lit(0)
    for c in chars:
        total = total + (F.length(text) - F.length(F.replace(text, F.lit(c), F.lit(""))))
    return total.cast("long")


def boilerplate(line: Column) -> Column:
    """Whether a line has a phrase of boilerplate; the pattern, slow at every place of a line, is tried only where a part of it is found."""

    def part(low: Column) -> Column:
        return functools.reduce(lambda a, b: a | b, [F.contains(low, F.lit(x)) for x in BOILERPLATE_PARTS])

    return F.exists(F.array(F.lower(line)), part) & line.rlike(BOILERPLATE)


def line_passes(line: Column, max_symbols: float = 0.5, max_pipes: int = 1, max_shouts: float = 0.5) -> Column:
    """Whether a line with words is prose: punctuation, navigation and boilerplate rules.

    It fails if it does not end like a sentence, has more than ``max_pipes``
    navigation bars, more symbols than ``max_symbols`` for each word, more
    doubled exclamation marks than ``max_shouts`` for each word, or a phrase of
    boilerplate.
    """
    words = F.size(F.split(F.btrim(line, F.lit(SPACES)), r"[\x20\x09-\x0D]+"))
    shouts = (F.length(line) - F.length(F.replace(line, F.lit("!!"), F.lit("")))) / 2
    return line.rlike(SENTENCE_END) & (_count(line, "|") <= max_pipes) & (_count(line, SYMBOLS) <= words * max_symbols) & (shouts <= words * max_shouts) & ~boilerplate(line)


def _after(ordered: Column, k: Column) -> Column:
    return F.try_element_at(ordered, k + 2)


def repeated_places(ordered: Column) -> Column:
    """Places of the three-word windows that occur twice or more, ascending.

    ``ordered`` has the windows' (h, place) pairs in order: equal neighbours
    are repeats.
    """
    return F.array_sort(
        F.filter(
            F.transform(
                ordered,
                lambda x, k: F.when(
                    (x["h"] == _after(ordered, k)["h"]) | ((k > 0) & (x["h"] == F.try_element_at(ordered, F.when(k > 0, k).otherwise(1))["h"])),
                    x["i"],
                ),
            ),
            lambda p: p.isNotNull(),
        )
    )


def window_text(w: Column, i: Column) -> Column:
    return F.concat_ws(" ", w[i], w[i + 1], w[i + 2])


def quality_features(docs: DataFrame, min_words: int = 50, max_repeat: int = 50, min_kept: float = 0.5, carry: list[Column] | None = None) -> DataFrame:
    """One row for each document with the base counts, the verdict and the text of the lines that stay.

    A null text has no words, fails the base rules and is not kept.  Rows with
    null or repeated ids stay rows of their own; columns of the input other
    than doc_id and text are read only for ``carry``, which are added as they
    are.  Blank lines are never judged and stay.
    """
    carry = carry or []
    names = [f"carried_{i}" for i in range(len(carry))]
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"), *[c.alias(n) for c, n in zip(carry, names, strict=True)])
    d = d.withColumn("words", F.regexp_extract_all("text", F.lit(WORD), F.lit(0)))
    d = d.withColumn("lines", F.split("text", "\n"))
    d = d.withColumn("full", F.filter("lines", lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    d = d.withColumn("n_words", F.size("words").cast("long"))
    w = F.col("words")
    d = d.withColumn("hashes", F.when(F.col("n_words") >= 4, F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.xxhash64(w[i], w[i + 1], w[i + 2]))))
    d = d.withColumn(
        "ordered",
        F.when(
            F.size(F.array_distinct("hashes")) < F.size("hashes"),
            F.sort_array(F.transform("hashes", lambda h, i: F.struct(h.alias("h"), i.alias("i")))),
        ),
    )
    # windows are grouped by a hash; where two that differ have the same one, by their words
    o = F.col("ordered")
    meet = F.transform(o, lambda x, k: (x["h"] == _after(o, k)["h"]) & (window_text(w, x["i"]) != window_text(w, _after(o, k)["i"])))
    d = d.withColumn("clash", F.coalesce(F.array_contains(meet, True), F.lit(False)))
    by_words = F.when(F.col("clash"), F.sort_array(F.transform("hashes", lambda h, i: F.struct(window_text(w, i).alias("h"), i.alias("i")))))
    d = d.withColumn("by_words", by_words)
    d = d.withColumn("places", F.when(F.col("clash"), repeated_places(F.col("by_words"))).otherwise(repeated_places(o)))
    p = F.col("places")
    d = d.select(
        "doc_id",
        "n_words",
        (F.length("text") - _count(F.col("text"), SPACES)).cast("long").alias("word_chars"),
        _count(F.col("text"), SYMBOLS).alias("n_symbols"),
        (F.size("full") - F.size(F.array_distinct("full"))).cast("long").alias("n_dup_lines"),
        F.coalesce(
            F.aggregate(F.transform(p, lambda x, k: F.coalesce(F.least(F.lit(3), F.try_element_at(p, k + 2) - x), F.lit(3))), F.lit(0).cast("long"), lambda a, x: a + x),
            F.lit(0),
        ).cast("long").alias("n_repeat_words"),
        F.filter("lines", lambda x: ~x.rlike(r"[^\x20\x09-\x0D]") | line_passes(x)).alias("good"),
        F.aggregate("full", F.lit(0).cast("long"), lambda a, x: a + F.length(x)).alias("full_chars"),
        *names,
    )
    d = d.withColumn("kept_chars", F.aggregate(F.filter("good", lambda x: x.rlike(r"[^\x20\x09-\x0D]")), F.lit(0).cast("long"), lambda a, x: a + F.length(x)))
    failed = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > max_repeat * F.col("n_words"))
    d = d.withColumn("base_failed", failed)
    kept = (~F.col("base_failed") & (F.col("kept_chars") >= min_kept * F.col("full_chars"))).alias("kept")
    d = d.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", kept, "full_chars", "kept_chars", F.array_join("good", "\n").alias("clean_text"), *names)
    # a generator is a fence: a caller's filter stays above it and does not evaluate the features anew for each array element
    return d.select(F.inline(F.array(F.struct(*d.columns))))


def clean_documents(docs: DataFrame, **rules) -> DataFrame:
    """The documents that stay, with their failing lines removed and n_chars renewed; all columns are kept."""
    others = [c for c in docs.columns if c not in ("doc_id", "text", "n_chars")]
    f = quality_features(docs, **rules, carry=[F.col(f"`{c}`") for c in others])
    f = f.where("kept")
    new = {"doc_id": F.col("doc_id"), "text": F.col("clean_text"), "n_chars": F.length("clean_text").cast("long")}
    new |= {c: F.col(f"carried_{i}") for i, c in enumerate(others)}
    return f.select(*[new[c].alias(c) for c in docs.columns])
