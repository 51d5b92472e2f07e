"""The paper's validation on micro cases and golden counts."""

import gzip
import os

import pytest
from pyspark.sql import functions as F

from dupflow import catalog, metrics
from dupflow.fixtures import alignments
from dupflow.functions import geometry as G
from dupflow.operators import baselines, codecs, compare, dupmark, pack, sortorder
from dupflow.plans.digest import digest
from dupflow.plans.pipeline import Pipeline, compile_plan
from dupflow.plans.plugins import DuplicateMarker, FlagFilter, MapqFilter, RegionFilter, load
from dupflow.plans.pool import choose_mode
from dupflow.sources import baf, taf

ORACLE_SAMPLE = ["blk_cut", "parse_fields", "mark_duplicates_full", "mark_frags", "mark_tie_sorted", "sort_coordinate", "pack_prefix", "baf_region_read", "mark_docs_exact", "flt_region_set", "jn_asof_window", "wn_rank", "m_paper_ratios"]


@pytest.mark.parametrize("name", ORACLE_SAMPLE)
def test_query_equals_sql(same, name):
    same(catalog.QUERIES, catalog.ORACLES, name)


def test_geometry(spark):
    rows = [(100, "3S20M1S", 0, 97), (100, "3S20M1S", 16, 120), (100, "2H3S5M", 0, 95), (10, "5M2D5M", 16, 21), (10, "5M1I5M", 16, 19)]
    df = spark.createDataFrame(rows, "pos long, cigar string, flag int, want long")
    assert df.where(G.unclipped_5p(F.col("pos"), F.col("cigar"), F.col("flag")) != F.col("want")).count() == 0


@pytest.mark.parametrize("own", ["end", "start"])
def test_blocks_hold_whole_lines_at_any_size(own):
    for data in (b"aa\nbbb\ncc", b"", b"\n\n\n", b"abcdefghij\n", b"a\r\nbc\r\n", b"x" * 50):
        lines = [x for x in data.split(b"\n")]
        lines = lines[:-1] if lines and lines[-1] == b"" else lines
        for size in range(1, 21):
            parts = taf.cut_positions(data, size, own)
            assert b"".join(data[a:b] for _, a, b in parts) == data
            got = [x for _, a, b in parts for x in data[a : b - (data[b - 1 : b] == b"\n")].split(b"\n")]
            assert got == lines
    assert [(a, b) for _, a, b in taf.cut_positions(b"aa\nbbb\ncc", 4, "end")] == [(0, 3), (3, 7), (7, 9)]
    assert [(a, b) for _, a, b in taf.cut_positions(b"aa\nbbb\ncc", 4, "start")] == [(0, 7), (7, 9)]


def test_block_source_and_line_places_agree(spark, tmp_path):
    text = "aa\nbbb\n\ncc dd ee\nlonger than one block by far\nz"
    (tmp_path / "t.taf").write_text(text)
    for own in ("end", "start"):
        a = taf.read_lines(spark, str(tmp_path / "t.taf"), 8, own).select("block_id", "start", "value")
        b = taf.line_places(spark.createDataFrame([(0, text)], "id int, text string"), "id", "text", 8, own).select("block_id", F.col("start").cast("long").alias("start"), "value")
        assert sorted(a.collect()) == sorted(b.collect())
        assert b"".join(r["bytes"] for r in taf.cut_blocks(spark, str(tmp_path / "t.taf"), 8, own).orderBy("start").collect()).decode() == text


def test_parse_modes(spark):
    good = "q\t99\tref1\t5\t3\t4M\t=\t9\t8\tACGT\tIIII\tNM:i:0"
    df = spark.createDataFrame([(good,), ("bad line",), ("@HD\tVN:1.5",)], "value string")
    assert taf.parse_taf(df).where("_corrupt is not null").count() == 1
    assert taf.parse_taf(df, "lenient").count() == 1
    with pytest.raises(Exception, match="bad alignment line"):
        taf.parse_taf(df, "strict").collect()


MICRO = "tid decimal(38,0), end_no int, flag int, ref_id int, pos long, u5 long, rev int, score long, lib string, seq decimal(38,0)"


def pair(t, score, a=(0, 100, 0), b=(0, 300, 1), pos=None, swap=False, lib="L"):
    x, y = (b, a) if swap else (a, b)
    return [(t, 1, 65, x[0], pos or x[1], x[1], x[2], score, lib, t * 10), (t, 2, 129, y[0], y[1], y[1], y[2], 0, lib, t * 10 + 1)]


def marked(spark, rows, **how):
    df = spark.createDataFrame([(*r,) for r in rows], MICRO.replace("decimal(38,0)", "long")).withColumn("tid", F.col("tid").cast("decimal(38,0)")).withColumn("seq", F.col("seq").cast("decimal(38,0)"))
    out = {}
    for m in ("agg", "window"):
        out[m] = sorted((int(r["tid"]), r["kind"]) for r in dupmark.mark_templates(df, how=m, **how).collect())
    assert out["agg"] == out["window"]
    return [t for t, _ in out["agg"]]


def test_marking_micro(spark):
    assert marked(spark, pair(1, 50) + pair(2, 60)) == [1]
    assert marked(spark, pair(1, 50) + pair(2, 50)) == [2]
    assert marked(spark, pair(1, 50) + pair(2, 60, b=(0, 300, 0))) == []
    assert marked(spark, pair(1, 50) + pair(2, 60, swap=True)) == [1]
    assert marked(spark, pair(1, 50) + pair(2, 60, pos=105)) == [1]
    assert marked(spark, pair(1, 50) + pair(2, 60, a=(0, 101, 0))) == []
    frag = [(3, 1, 73, 0, 100, 100, 0, 99, "L", 30), (3, 2, 133, -1, 0, 0, 0, 0, "L", 31)]
    assert marked(spark, pair(1, 50) + frag) == [3]
    lone = [(4, 1, 73, 5, 7, 7, 0, 10, "L", 40), (5, 1, 73, 5, 7, 7, 0, 20, "L", 50)]
    assert marked(spark, lone) == [4]
    assert marked(spark, [(6, 1, 321, 0, 100, 100, 0, 1, "L", 60)] + pair(1, 50)) == []
    assert marked(spark, pair(1, 50, lib="A") + pair(2, 60, lib="B"), by_library=True) == []
    assert marked(spark, pair(1, 50, pos=100) + pair(2, 50, pos=90), tie="sorted") == [1]
    assert marked(spark, pair(1, 50, pos=100) + pair(2, 50, pos=90), tie="input") == [2]
    assert marked(spark, []) == []


def test_golden_counts(spark, sf):
    d = digest(alignments(spark, sf)).cache()
    m = dupmark.mark_templates(d)
    assert {r["kind"]: r["n"] for r in m.groupBy("kind").agg(F.count("*").alias("n")).collect()} == {"pair": 786, "fragment": 278}
    assert dupmark.mark_records(d).count() == 1850
    assert dupmark.tie_sets(dupmark.collapse(d, coarse=64)).count() == 143
    lib = dupmark.mark_templates(d, by_library=True)
    assert sorted(r["n"] for r in lib.groupBy("kind").agg(F.count("*").alias("n")).collect()) == [176, 301]


def test_marking_clears_stale_bits_and_is_idempotent(spark, sf):
    a = alignments(spark, sf)
    once = dupmark.apply_marks(a.withColumn("flag", F.expr("flag | 1024")), dupmark.mark_records(digest(a)))
    twice = dupmark.apply_marks(once, dupmark.mark_records(digest(once)))
    assert once.where("flag & 1024 <> 0").count() == 1850
    assert compare.differences(once, twice).first()[:] == (0, 0)


def test_salted_marking_equals_plain(spark, sf):
    e = spark.read.parquet(f"{sf}/events.parquet").selectExpr("event_id", "event_type", "cast(round(value) as bigint) score")
    a = dupmark.mark_keyed(e, ["event_type"], F.col("score"), F.col("event_id"))
    b = dupmark.mark_keyed(e, ["event_type"], F.col("score"), F.col("event_id"), salt=8)
    assert sorted(a.collect()) == sorted(b.collect())


def test_plan_kinds_and_shapes(spark, sf):
    a = alignments(spark, sf)
    stream = Pipeline(a).attach(RegionFilter(3, 2000, 5000)).attach(MapqFilter(5))
    assert compile_plan(stream.plugins).kind == "stream"
    assert metrics.exchanges(stream.run()) == []
    p = compile_plan([FlagFilter(exclude=256), DuplicateMarker()])
    assert p.kind == "pooled" and p.indexes == {"clipped", "unclipped"}
    out = sortorder.overlay_sorted(a, dupmark.mark_records(digest(a)))
    fat = [x for x in metrics.exchanges(out) if "rangepartitioning" in x]
    assert len(fat) == 1
    assert load("dupflow.plans.plugins:MapqFilter", minimum=3).predicate() is not None
    assert choose_mode(100, 1000) == "memory" and choose_mode(1000, 1000) == "storage"
    d = spark.read.parquet(f"{sf}/lineitem.parquet").where("l_quantity >= 45").select("l_partkey")
    assert "GreaterThanOrEqual(l_quantity" in d._jdf.queryExecution().executedPlan().toString()


def test_greedy_packing():
    k = 1000
    assert pack.greedy_blocks([40 * k, 30 * k, 20 * k, 10 * k], 65536) == [0, 1, 1, 1]
    assert pack.greedy_blocks([70 * k, 1, 70 * k], 65536) == [0, 1, 2]
    assert pack.greedy_blocks([]) == []


def test_codec_lanes_give_the_same_bytes():
    raw = os.urandom(1000) * 20
    for name in codecs.detect_codecs():
        assert gzip.decompress(codecs.codec(name).compress(raw)) == raw



def test_one_thread_tools_agree_with_the_pipeline(spark, sf, tmp_path):
    path = str(tmp_path / "taf")
    taf.render_taf(alignments(spark, sf)).repartitionByRange(3, "seq").sortWithinPartitions("seq").select("value").write.text("file://" + path)
    baselines.sort_tool(path, str(tmp_path / "sorted"))
    n = baselines.mark_tool(str(tmp_path / "sorted"), str(tmp_path / "marked"))
    records, header = taf.read_taf(spark, path)
    ours = {r["value"] for r in taf.render_taf(Pipeline(records).attach(DuplicateMarker()).run()).collect()}
    lines = [line for _, line in baselines._read_blocks(str(tmp_path / "marked"))]
    assert set(lines) == ours and n == sum(int(x.split("\t")[1]) >> 10 & 1 for x in lines) == 1850
    assert header.lines == [] and baselines.loop_convert(path, str(tmp_path / "a"), 1) == baselines.loop_convert(path, str(tmp_path / "b"), 3, 5)


def test_region_reads_open_only_blocks_that_hold_the_region(spark, sf, tmp_path):
    a = alignments(spark, sf)
    for how, records in (("unsorted", a), ("sorted", sortorder.sorted_scan(a, 3))):
        out = f"file://{tmp_path}/{how}"
        total = baf.write_baf(records, out, limit=4096).count()
        opened = baf.index_of(spark, out, (3, 2000, 5000)).count()
        got = RegionFilter(3, 2000, 5000).apply(baf.read_baf(spark, out, (3, 2000, 5000))).count()
        assert got == RegionFilter(3, 2000, 5000).apply(a).count() == 3 and opened <= 3 < total


def test_a_copy_without_the_training_data_folders_works(tmp_path):
    import shutil
    import subprocess
    import sys

    here = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    copy = tmp_path / "copy"
    shutil.copytree(here, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", "corpus_pipeline.py"))
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 150 and set(o) <= set(q) and not any(n.startswith('op1_') or n == 'pipeline' for n in q)"
    subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, env={**os.environ, "PYTHONPATH": str(copy)})


def test_parts_concatenate(spark, sf, tmp_path):
    out = "file://" + str(tmp_path / "baf")
    a = sortorder.sorted_scan(alignments(spark, sf).limit(500), 3)
    index = baf.write_baf(a, out)
    assert index.where("raw_len > 65536 and n_rec > 1").count() == 0
    baf.concat_parts(out, str(tmp_path / "one.baf"))
    whole = list(baf.block_records(gzip.decompress((tmp_path / "one.baf").read_bytes())))
    assert len(whole) == 500


def test_compare_sees_one_flipped_bit(spark, sf):
    from dupflow.queries.methods import perturbed

    a = alignments(spark, sf).limit(200).withColumn("flag", F.expr("flag | 1024")).cache()
    assert compare.verdict(a, perturbed(a)).first()["accurate"]
    seq = a.agg(F.min("seq")).first()[0]
    b = a.withColumn("flag", F.when(F.col("seq") == F.lit(seq), F.expr("flag & ~1024")).otherwise(F.col("flag")))
    assert compare.differences(a, b).first()[:] == (1, 0)


def test_brute_force_agrees(spark, sf):
    d = digest(alignments(spark, sf))
    p = dupmark.pairs(dupmark.collapse(d)).where("ra = 1").select("tid")
    small = d.join(p, "tid", "left_semi").cache()
    a = {r["tid"] for r in dupmark.mark_pairs(dupmark.collapse(small)).collect()}
    assert a == {r["tid"] for r in dupmark.brute_mark(small).collect()} and a


def test_entry_without_training_data():
    import __spark_entry__ as e

    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q) and len(q) > 100
    assert metrics.amdahl(0.8, 1e9) == pytest.approx(5)


def test_last_click_by_subquery_is_an_equal_join(spark, sf, same):
    """Rows must not grow with the purchases times the clicks of a user."""
    assert len(same(catalog.QUERIES, catalog.ORACLES, "jn_asof_lateral")) > 0
    plan = catalog.QUERIES["jn_asof_lateral"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    joins = [x for x in plan.splitlines() if "Join " in x]
    assert joins and not any(" < " in x or " > " in x for x in joins)


def test_unmarked_records_stay_where_they_are(spark, sf):
    """Only records that the sieve cannot clear are shuffled to meet the marks."""
    old = {k: spark.conf.get(k) for k in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.enabled")}
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        a = alignments(spark, sf)
        marks = dupmark.mark_records(digest(a))
        want = {r["seq"] for r in marks.select("seq").collect()}
        out = dupmark.apply_marks(a.withColumn("mapq", F.spark_partition_id()), marks).select("seq", "flag", F.col("mapq").alias("home"), F.spark_partition_id().alias("at")).collect()
    finally:
        for k, v in old.items():
            spark.conf.set(k, v)
    assert len(out) == a.count() and {r["seq"] for r in out if r["flag"] & 1024} == want and want
    places = {}
    for r in out:
        if not r["flag"] & 1024:
            places.setdefault(r["home"], []).append(r["at"])
    stayed = sum(max(x.count(p) for p in set(x)) for x in places.values())
    assert stayed >= 0.99 * (len(out) - len(want))


@pytest.mark.parametrize("name", ["m_speedup", "m_paper_ratios", "m_thread_scaling", "m_amdahl"])
def test_measures_come_from_a_given_table(spark, sf, same, name):
    assert len(same(catalog.QUERIES, catalog.ORACLES, name)) > 0
    assert any("lineitem" in f for f in catalog.QUERIES[name](spark, sf).inputFiles())


def _shuffle_files(spark):
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {files.apply(i).getName() for i in range(files.size()) if files.apply(i).getName().startswith("shuffle_")}


def test_shuffle_files_go_with_the_write(spark, tmp_path):
    from dupflow.shared import CLEAN_UP, write_then_free

    before, setting = _shuffle_files(spark), spark.conf.get(CLEAN_UP)
    write_then_free(spark, lambda: spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count().write.parquet(f"file://{tmp_path}/t"), after=1e9)
    assert not _shuffle_files(spark) - before
    assert spark.conf.get(CLEAN_UP) == setting
    assert spark.read.parquet(f"file://{tmp_path}/t").agg(F.sum("count")).first()[0] == 1000


def test_marks_shuffle_digests_once(spark, sf):
    """What follows the templates reads them from storage, however many branches it has."""
    d = digest(alignments(spark, sf))
    m = dupmark.mark_records(d)
    assert not set(m.inputFiles()) & set(d.inputFiles())
    want = dupmark.mark_templates(d).join(dupmark.eligible(d), "tid").select("seq")
    assert sorted(r[0] for r in m.select("seq").collect()) == sorted(r[0] for r in want.collect())


def test_shared_keys_keeps_every_shared_key(spark):
    rows = spark.range(20_000).selectExpr("id", "if(id % 10 < 4, id div 2, id) a", "if(id % 3 = 0, null, 1) b")
    shared = rows.groupBy("a", "b").agg(F.count("*").alias("n")).where("n > 1")
    want = {r[0] for r in rows.join(shared, rows["a"].eqNullSafe(shared["a"]) & rows["b"].eqNullSafe(shared["b"])).select("id").collect()}
    kept = {r[0] for r in dupmark.shared_keys(rows, ["a", "b"]).select("id").collect()}
    assert want and want <= kept and len(kept) < 20_000


def test_stored_records_are_not_pooled_again(spark, sf):
    from dupflow.plans.pool import is_stored, pool_once

    a = alignments(spark, sf)
    assert is_stored(a) and not is_stored(a.where("mapq > 3")) and not is_stored(spark.read.parquet(f"{sf}/lineitem.parquet"))
    assert pool_once(a) is a
    held = pool_once(a, "memory")
    assert not held.storageLevel.useDisk and held.count() == a.count()
    held.unpersist()
    assert pool_once(a.where("mapq > 3"), "memory").storageLevel.useDisk
    spark.catalog.clearCache()


def test_text_files_are_read_in_columns(spark, sf, tmp_path, monkeypatch):
    from dupflow.queries import methods
    from dupflow.sources import taf

    data = "@HD\tx\r\n@é\n".encode() + b"bad \xff byte\n\n" + "last é".encode()
    (tmp_path / "a").write_bytes(data)
    lines, at = [x.decode("utf-8", "replace") for x in data.split(b"\n")], [0]
    for x in data.split(b"\n"):
        at.append(at[-1] + len(x) + 1)
    got = taf.read_lines(spark, str(tmp_path / "a"), 4096).sort("start").collect()
    assert [(r["line_no"], r["start"], r["length"], r["value"]) for r in got] == [(i, at[i], at[i + 1] - at[i] - 1, x) for i, x in enumerate(lines)]

    class NoRows:
        def inputFiles(self):
            return ["file://" + str(tmp_path / "a")]

    class Text:
        _jvm, _jsc = spark._jvm, spark._jsc
        read = type("Read", (), {"text": lambda self, path: NoRows()})()

    assert taf.read_header(Text(), str(tmp_path)).lines == ["@HD\tx", "@é"]
    monkeypatch.setattr(methods, "FILE_BYTES", 2000, raising=False)
    assert len(taf.data_files(methods.taf_files(spark, sf))) > 5
