"""Cost measures: time, memory, rates, ratios and the serial-fraction bound."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

@contextmanager
def timed(stage: str, into: list):
    t = time.perf_counter()
    yield
    into.append({"stage": stage, "millis": round((time.perf_counter() - t) * 1000), "peak_kb": peak_kb()})


def peak_kb() -> int:
    """Peak resident size of this process."""
    with open("/proc/self/status") as f:
        return next((int(line.split()[1]) for line in f if line.startswith("VmHWM")), 0)


def speedup(base: float, new: float) -> float:
    return base / new


def amdahl(parallel: float, workers: float) -> float:
    """Bound on the speed-up when a share of the time is parallel."""
    return 1 / ((1 - parallel) + parallel / workers)


def costs(lines: DataFrame) -> DataFrame:
    """(input, config, cost, cents): the cost of each run in whole units, an input being a return flag and a configuration a line number."""
    return lines.groupBy(F.col("l_returnflag").alias("input"), F.col("l_linenumber").alias("config")).agg(F.expr("sum(cast(l_quantity as bigint)) cost"), F.expr("sum(cast(round(l_extendedprice * 100) as bigint)) cents"))


def speedups(runs: DataFrame, base: int) -> DataFrame:
    """Speed-up of each configuration over ``base``, by input."""
    first = runs.where(F.col("config") == base).select("input", F.col("cost").alias("base"))
    return runs.join(first, "input").selectExpr("input", "config", "cast((100 * base) div nullif(cost, 0) as double) / 100 speedup")


def ratios(runs: DataFrame) -> DataFrame:
    """(measure, value) of each input: the gain of the second configuration, the slow-down from the third to the second, cents for each unit."""
    c = runs.groupBy("input").agg(*[F.max(F.when(F.col("config") == i, F.col("cost"))).alias(f"c{i}") for i in (1, 2, 3)], F.sum("cents").alias("cents"), F.sum("cost").alias("cost"))
    each = "stack(3, 'gain_' || input, (1000 * c1) div nullif(c2, 0) - 1000, 'slowdown_' || input, (1000 * c2) div nullif(c3, 0) - 1000, 'cents_per_unit_' || input, (1000 * cents) div nullif(cost, 0)) as (measure, v)"
    return c.selectExpr(each).selectExpr("measure", "cast(v as double) / 1000 value")


def scaling(runs: DataFrame) -> DataFrame:
    """Cost by number of threads, relative to one thread."""
    t = runs.groupBy(F.col("config").alias("threads")).agg(F.sum("cost").alias("cost"))
    one = t.where("threads = 1").select(F.col("cost").alias("one"))
    return t.crossJoin(F.broadcast(one)).selectExpr("threads", "cost", "cast((100 * cost) div nullif(one, 0) as double) / 100 relative", "cast((100 * one) div nullif(cost, 0) as double) / 100 speedup")


def bounds(lines: DataFrame) -> DataFrame:
    """The serial-fraction bound by workers; the parallel share of the cost is that of the finished lines."""
    q = F.expr("cast(l_quantity as bigint)")
    t = lines.agg(F.sum(F.when(F.col("l_linestatus") == "F", q)).alias("shared"), F.sum(q).alias("total"))
    workers = lines.select(F.col("l_linenumber").cast("long").alias("workers")).distinct()
    return workers.crossJoin(F.broadcast(t)).selectExpr("workers", "cast((10000 * total * workers) div nullif((total - shared) * workers + shared, 0) as double) / 10000 bound")


def gc_share(spark: SparkSession) -> float:
    """Garbage collection time of this JVM as a share of its uptime."""
    beans = spark._jvm.java.lang.management.ManagementFactory
    spent = sum(b.getCollectionTime() for b in beans.getGarbageCollectorMXBeans())
    return spent / max(1, beans.getRuntimeMXBean().getUptime())


def exchanges(df: DataFrame) -> list[str]:
    """The exchanges of a frame's physical plan, for plan tests."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return [x.strip() for x in text.splitlines() if "Exchange " in x and "BroadcastExchange" not in x and "ReusedExchange" not in x]
