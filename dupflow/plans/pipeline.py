"""A pipeline: source, plug-ins in order, sink; the plan follows from the kinds of plug-ins."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from dupflow.operators.sortorder import overlay_sorted, sorted_scan
from dupflow.plans.digest import digest
from dupflow.plans.plugins import AnalyzerPlugin, Plugin
from dupflow.plans.pool import available_storage, choose_mode, input_bytes, pool_once


@dataclass
class Plan:
    """``stream``: narrow, input order kept; ``pooled``: pool, index, analyze, sorted output."""

    kind: str
    filters: list
    analyzers: list
    codec: str
    indexes: set = field(default_factory=set)


def compile_plan(plugins: list[Plugin]) -> Plan:
    """Only filters: no pool, no index, no shuffle.  Any analyzer: all input is pooled first."""
    analyzers = [p for p in plugins if p.kind == "analyzer"]
    kinds = set().union(*[a.index_kinds() for a in analyzers]) if analyzers else set()
    codecs = [p.codec() for p in plugins if p.kind == "accelerator"]
    return Plan("pooled" if analyzers else "stream", [p for p in plugins if p.kind == "filter"], analyzers, codecs[-1] if codecs else "software", kinds)


class Pipeline:
    """``Pipeline(records).attach(p).attach(q).run()`` gives the output records in output order."""

    def __init__(self, records: DataFrame, mode: str = "storage", path: str | None = None, size: int | None = None):
        """``mode`` is ``memory``, ``storage`` or ``auto``: memory if ``size`` bytes of input fit there."""
        if mode == "auto":
            if size is None:
                raise ValueError("the automatic choice needs the size of the input")
            mode = choose_mode(size, available_storage(records.sparkSession))
        self.records, self.mode, self.path = records, mode, path
        self.plugins: list[Plugin] = []

    def attach(self, plugin: Plugin) -> Pipeline:
        self.plugins.append(plugin)
        return self

    def filtered(self, plan: Plan) -> DataFrame:
        """Filters come before the pool, so what they drop is never pooled."""
        out = self.records
        for f in plan.filters:
            out = f.apply(out)
        return out

    def run(self) -> DataFrame:
        plan = compile_plan(self.plugins)
        out = self.filtered(plan)
        if plan.kind == "stream":
            return out
        pooled = pool_once(out, self.mode, self.path)
        marks = None
        for a in plan.analyzers:
            made = a.marks(digest(pooled, a.extras()))
            if made is not None:
                marks = made if marks is None else marks.unionByName(made)
        return sorted_scan(pooled) if marks is None else overlay_sorted(pooled, marks.distinct() if len(plan.analyzers) > 1 else marks)

    def analyses(self) -> list[DataFrame]:
        """The analyzers' own results."""
        plan = compile_plan(self.plugins)
        pooled = pool_once(self.filtered(plan), self.mode, self.path)
        return [a.analyze(digest(pooled, a.extras())) for a in plan.analyzers if isinstance(a, AnalyzerPlugin)]

    def write(self, out: str, header=None, program: str = "dupflow") -> DataFrame:
        """Runs and writes block-compressed files, the input's header with them; returns the block index."""
        from dupflow.sources.baf import write_baf

        plan = compile_plan(self.plugins)
        kept = header and header.with_program(program, "coordinate" if plan.kind == "pooled" else None)
        return write_baf(self.run(), out, plan.codec, header=kept)


def convert_files(spark: SparkSession, path: str, out: str, plugins: list[Plugin], mode: str = "auto") -> DataFrame:
    """File to file: reads text alignments with their header, runs the plug-ins, writes block files; returns the block index."""
    from dupflow.sources.taf import read_taf

    records, header = read_taf(spark, path)
    p = Pipeline(records.drop("_corrupt"), mode, size=input_bytes(spark, path))
    for x in plugins:
        p.attach(x)
    return p.write(out, header)
