"""Plug-ins that attach to a pipeline at run time: filters, accelerators, analyzers."""

from __future__ import annotations

import importlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dupflow import schema as S
from dupflow.functions.geometry import has, overlaps, span
from dupflow.operators import dupmark


class Plugin:
    """kind is ``filter``, ``accelerator`` or ``analyzer``."""

    kind = "plugin"

    def __init__(self, **params):
        self.params = params
        self.name = type(self).__name__


class FilterPlugin(Plugin):
    """Keeps records that meet a condition; as a Column it is pushed down to the scan."""

    kind = "filter"

    def predicate(self) -> Column | None:
        return None

    def apply(self, records: DataFrame) -> DataFrame:
        p = self.predicate()
        return records if p is None else records.where(p)


class AcceleratorPlugin(Plugin):
    """Names the codec that the writer uses."""

    kind = "accelerator"

    def codec(self) -> str:
        return self.params.get("codec", "dual")


class AnalyzerPlugin(Plugin):
    """Needs all input pooled; its marks change records before they are written."""

    kind = "analyzer"

    def extras(self) -> dict[str, Column]:
        """Summaries of long parts to keep in the digest."""
        return {}

    def index_kinds(self) -> set[str]:
        return {"clipped"}

    def analyze(self, digests: DataFrame) -> DataFrame:
        raise NotImplementedError

    def marks(self, digests: DataFrame) -> DataFrame | None:
        return None


class RegionFilter(FilterPlugin):
    """Records that cover any base of a reference interval."""

    def __init__(self, ref: int, start: int, end: int):
        super().__init__(ref=ref, start=start, end=end)

    def predicate(self) -> Column:
        return overlaps(F.col("ref_id"), F.col("pos"), F.col("cigar"), self.params["ref"], self.params["start"], self.params["end"])


class RegionSetFilter(FilterPlugin):
    """Records that touch any interval of a panel (ref, start, end); rows and their order stay as they are.

    A record that spans at most ``bin_size`` bases is looked up by the bin of
    its start alone, as the panel lists each interval in one bin more; the few
    longer ones are held against all intervals of their reference.  Both are
    semi-joins whose panel side is broadcast by the engine's own size check, so
    the records are neither exploded nor shuffled.
    """

    def __init__(self, regions: DataFrame, bin_size: int = 1000):
        super().__init__(regions=regions, bin_size=bin_size)

    def apply(self, records: DataFrame) -> DataFrame:
        b, regions = self.params["bin_size"], self.params["regions"]
        panel = regions.select(F.col("ref").alias("p_ref"), F.col("start").alias("p_start"), F.col("end").alias("p_end"))
        bins = panel.select("*", F.explode(F.sequence(F.floor(F.col("p_start") / b) - 1, F.floor(F.col("p_end") / b))).alias("p_bin"))
        covered = F.greatest(span(F.col("cigar")), F.lit(1))
        touches = (F.col("ref_id") == F.col("p_ref")) & (F.col("pos") <= F.col("p_end")) & (F.col("pos") + covered - 1 >= F.col("p_start"))
        short = records.where(covered <= b).join(bins, touches & (F.floor(F.col("pos") / b) == F.col("p_bin")), "left_semi")
        return short.unionAll(records.where(covered > b).join(panel, touches, "left_semi"))


class FlagFilter(FilterPlugin):
    def __init__(self, require: int = 0, exclude: int = 0):
        super().__init__(require=require, exclude=exclude)

    def predicate(self) -> Column:
        f = F.col("flag")
        return (f.bitwiseAND(F.lit(self.params["require"])) == self.params["require"]) & (f.bitwiseAND(F.lit(self.params["exclude"])) == 0)


class MapqFilter(FilterPlugin):
    def __init__(self, minimum: int):
        super().__init__(minimum=minimum)

    def predicate(self) -> Column:
        return F.col("mapq") >= self.params["minimum"]


class AntiFilter(FilterPlugin):
    """Drops records whose key is in a table of keys."""

    def __init__(self, keys: DataFrame, on: list[str]):
        super().__init__(keys=keys, on=on)

    def apply(self, records: DataFrame) -> DataFrame:
        return records.join(self.params["keys"], self.params["on"], "left_anti")


class DuplicateMarker(AnalyzerPlugin):
    """The flagship analyzer; needs the unclipped index as well."""

    def index_kinds(self) -> set[str]:
        return {"clipped", "unclipped"}

    def analyze(self, digests: DataFrame) -> DataFrame:
        return dupmark.mark_templates(digests, **self.params)

    def marks(self, digests: DataFrame) -> DataFrame:
        return dupmark.mark_records(digests, **self.params)


class CoverageAnalyzer(AnalyzerPlugin):
    """Records that touch each bin of the reference."""

    def __init__(self, bin_size: int = 1000):
        super().__init__(bin_size=bin_size)

    def extras(self) -> dict[str, Column]:
        return {"span": span(F.col("cigar"))}

    def analyze(self, digests: DataFrame) -> DataFrame:
        b = self.params["bin_size"]
        d = digests.where((F.col("ref_id") >= 0) & ~has(F.col("flag"), S.UNMAPPED))
        bins = d.select("ref_id", F.explode(F.sequence(F.floor(F.col("pos") / b), F.floor((F.col("pos") + F.col("span") - 1) / b))).alias("bin"))
        return bins.groupBy("ref_id", "bin").agg(F.count("*").alias("depth"))


class FlagStat(AnalyzerPlugin):
    """Counts of records by what their flags say."""

    def analyze(self, digests: DataFrame) -> DataFrame:
        f = F.col("flag")
        n = lambda c, name: F.count_if(c).alias(name)
        return digests.agg(F.count("*").alias("total"), n(~has(f, S.UNMAPPED), "mapped"), n(has(f, S.PROPER), "proper"), n(has(f, S.SECONDARY), "secondary"), n(has(f, S.REVERSE), "reversed"), n(has(f, S.END1), "first_ends"), n(has(f, S.DUPLICATE), "duplicates"))


class InsertSize(AnalyzerPlugin):
    """Count, mean in hundredths and extremes of positive template lengths by library."""

    def extras(self) -> dict[str, Column]:
        return {"tlen": F.col("tlen")}

    def analyze(self, digests: DataFrame) -> DataFrame:
        d = digests.where((F.col("tlen") > 0) & ~has(F.col("flag"), S.SECONDARY))
        return d.groupBy("lib").agg(F.count("*").alias("n"), F.floor(F.sum("tlen") * 100 / F.count("*")).cast("long").alias("mean_x100"), F.min("tlen").alias("low"), F.max("tlen").alias("high"))


def load(spec: str, **params) -> Plugin:
    """A plug-in from ``package.module:Class``."""
    module, _, name = spec.partition(":")
    return getattr(importlib.import_module(module), name)(**params)
