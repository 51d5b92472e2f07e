"""Queries of the paper's methods, variants, baselines and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dupflow import metrics
from dupflow.fixtures import AL, alignments, marks_sql
from dupflow.functions import geometry as G
from dupflow.operators import baselines, compare, dupmark, pack, sortorder
from dupflow.operators.dupmark import PAIR_KEY
from dupflow.plans import pool as P
from dupflow.plans.digest import digest
from dupflow.plans.pipeline import Pipeline, convert_files
from dupflow.plans.plugins import CoverageAnalyzer, DuplicateMarker, FlagFilter, FlagStat, InsertSize, MapqFilter, RegionFilter, RegionSetFilter
from dupflow.registry import query, table
from dupflow.shared import shared_path, write_then_free
from dupflow.sources import baf, taf

FILTER_REGION = (3, 2000, 5000)
CORE = ["qname", "flag", "ref_id", "pos", "mapq", "cigar", "mate_ref_id", "mate_pos", "tlen", "bases", "quals"]
CORE_SQL = ", ".join(CORE)


def tag_text():
    return F.array_join(F.transform("tags", lambda t: F.concat_ws(":", t["tag"], t["type"], t["value"])), "\t").alias("tagtext")


def shown(records: DataFrame) -> DataFrame:
    """Records as plain columns, for comparison."""
    return records.select(*CORE, tag_text(), "lib")


def dg(spark, sf) -> DataFrame:
    return digest(alignments(spark, sf))


def st(c: str):
    return F.col(c).cast("string").alias(c)


SHOWN = f"SELECT {CORE_SQL}, tagtext, lib FROM "

# ---- ingest ---------------------------------------------------------------

_LINES = """WITH d AS (SELECT doc_id, octet_length(encode(coalesce(text, ''))) AS size, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
e AS (SELECT doc_id, size, i - 1 AS line_no, ls[i] AS value, (i - 1 + coalesce(list_sum(list_transform(ls[1:i-1], lambda x: octet_length(encode(x)))), 0))::BIGINT AS start FROM (SELECT *, unnest(range(1, len(ls) + 1)) AS i FROM d)),
f AS (SELECT *, octet_length(encode(value)) AS length FROM e WHERE start < size OR octet_length(encode(value)) > 0)
"""


def _docs(spark, sf) -> DataFrame:
    return table(spark, sf, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("text"))


def _blocks(lines: DataFrame) -> DataFrame:
    return lines.groupBy(F.col("file_id").alias("doc_id"), "block_id").agg(F.count("*").alias("n_lines"), F.min("start").cast("long").alias("first_byte"), F.sum(F.col("length") + 1).alias("bytes"))


def _blk_sql(byte: str, size: int) -> str:
    return f"{_LINES} SELECT doc_id, floor(({byte}) / {size})::BIGINT AS block_id, count(*) AS n_lines, min(start)::BIGINT AS first_byte, sum(length + 1)::BIGINT AS bytes FROM f GROUP BY 1, 2"


LAST = "least(start + length, size - 1)"


@query(_blk_sql(LAST, 1024))
def blk_cut(spark, sf):
    return _blocks(taf.line_places(_docs(spark, sf), "doc_id", "text", 1024, "end"))


@query(_blk_sql("start", 1024))
def blk_cut_start(spark, sf):
    return _blocks(taf.line_places(_docs(spark, sf), "doc_id", "text", 1024, "start"))


@query(" UNION ALL ".join(f"SELECT {n}::BIGINT AS block_bytes, (SELECT count(*) FROM ({_blk_sql(LAST, n)})) AS n_blocks, (SELECT sum(n_lines)::BIGINT FROM ({_blk_sql(LAST, n)})) AS n_lines" for n in (64, 1024, 65536)))
def blk_size_sweep(spark, sf):
    out = None
    for n in (64, 1024, 65536):
        b = _blocks(taf.line_places(_docs(spark, sf), "doc_id", "text", n, "end")).agg(F.count("*").alias("n_blocks"), F.sum("n_lines").alias("n_lines")).select(F.lit(n).cast("long").alias("block_bytes"), "n_blocks", "n_lines")
        out = b if out is None else out.unionAll(b)
    return out


@query(_LINES + " SELECT doc_id, line_no::BIGINT AS line_no, start, length::BIGINT AS length, md5(value) AS digest FROM f")
def line_split(spark, sf):
    return taf.line_places(_docs(spark, sf), "doc_id", "text", 65536).select(F.col("file_id").alias("doc_id"), F.col("line_no").cast("long").alias("line_no"), F.col("start").cast("long").alias("start"), F.col("length").cast("long").alias("length"), F.md5("value").alias("digest"))


@query(_LINES + " SELECT count(*) AS n_lines, sum(length)::BIGINT AS bytes, max(length)::BIGINT AS longest, count(*) FILTER (WHERE length = 0) AS empty FROM f")
def line_stats(spark, sf):
    return taf.line_places(_docs(spark, sf), "doc_id", "text", 65536).agg(F.count("*").alias("n_lines"), F.sum("length").cast("long").alias("bytes"), F.max("length").cast("long").alias("longest"), F.count_if(F.col("length") == 0).alias("empty"))


_TAF = """concat_ws(chr(9), qname, flag, CASE WHEN ref_id < 0 THEN '*' ELSE 'ref' || ref_id END, pos, mapq, cigar,
  CASE WHEN mate_ref_id = ref_id AND ref_id >= 0 THEN '=' WHEN mate_ref_id < 0 THEN '*' ELSE 'ref' || mate_ref_id END, mate_pos, tlen, bases, quals, tagtext)"""


@query(AL + f"SELECT seq::VARCHAR AS seq, {_TAF} AS value FROM al")
def render_taf(spark, sf):
    return taf.render_taf(alignments(spark, sf)).select(st("seq"), "value")


@query(AL + f"SELECT {CORE_SQL}, tagtext FROM al")
def parse_fields(spark, sf):
    return taf.parse_taf(taf.render_taf(alignments(spark, sf))).select(*CORE, tag_text())


@query("SELECT 0::BIGINT AS lost, 0::BIGINT AS made, 0::BIGINT AS corrupt")
def parse_roundtrip(spark, sf):
    a = alignments(spark, sf)
    p = taf.parse_taf(taf.render_taf(a))
    x, y = a.select(*CORE, tag_text()), p.select(*CORE, tag_text())
    both = x.groupBy(*x.columns).agg(F.count("*").alias("n"), F.lit(0).alias("m")).unionAll(y.groupBy(*y.columns).agg(F.lit(0).cast("long").alias("n"), F.count("*").cast("int").alias("m")))
    each = both.groupBy(*x.columns).agg(F.sum("n").alias("n"), F.sum("m").alias("m"))
    return each.agg(F.sum(F.greatest(F.col("n") - F.col("m"), F.lit(0))).cast("long").alias("lost"), F.sum(F.greatest(F.col("m") - F.col("n"), F.lit(0))).cast("long").alias("made")).crossJoin(p.agg(F.count("_corrupt").alias("corrupt")))


@query(_LINES + f" SELECT doc_id, line_no::BIGINT AS line_no, ((floor({LAST} / 1024)::BIGINT << 33) | line_no)::BIGINT AS seq FROM f")
def seq_order(spark, sf):
    """Block number and local number packed; monotone in the input order of each file."""
    lines = taf.line_places(_docs(spark, sf), "doc_id", "text", 1024)
    return taf.with_sequence(lines, "block_local").select(F.col("file_id").alias("doc_id"), F.col("line_no").cast("long").alias("line_no"), "seq")


@query(AL + "SELECT ref_id, pos, min(seq)::VARCHAR AS first_seq, count(*) AS n FROM al WHERE ref_id >= 0 GROUP BY 1, 2")
def first_seen(spark, sf):
    return alignments(spark, sf).where("ref_id >= 0").groupBy("ref_id", "pos").agg(F.min("seq").cast("string").alias("first_seq"), F.count("*").alias("n"))


@query("SELECT count(*) * 2 + count(*) FILTER (WHERE l_quantity = 50 AND round(l_discount * 100) < 9) AS n FROM lineitem")
def bench_parse_par(spark, sf):
    return taf.parse_taf(taf.render_taf(alignments(spark, sf))).where("_corrupt is null and flag >= 0 and pos >= 0").agg(F.count("*").alias("n"))


@query("SELECT count(*) * 2 + count(*) FILTER (WHERE l_quantity = 50 AND round(l_discount * 100) < 9) AS n FROM lineitem")
def bench_parse_seq(spark, sf):
    return baselines.sequential_parse(taf.render_taf(alignments(spark, sf))).select("n")


@query(AL + f"SELECT {CORE_SQL}, tagtext FROM al")
def src_taf(spark, sf):
    """Lines written as text, read back through the byte-block source and parsed."""
    path = shared_path(spark, "taf")
    taf.render_taf(alignments(spark, sf)).select("value").write.text(path)
    return taf.parse_taf(taf.read_lines(spark, path, 65536)).select(*CORE, tag_text())


# ---- pool and index --------------------------------------------------------


@query(AL + SHOWN + "al")
def pool_memory(spark, sf):
    return shown(P.pool(alignments(spark, sf), "memory"))


@query(AL + SHOWN + "al")
def pool_storage(spark, sf):
    return shown(P.pool(alignments(spark, sf), "storage"))


_OVER = "ref_id = 3 AND pos <= 5000 AND pos + sp - 1 >= 2000"


@query(AL + SHOWN + f"al WHERE {_OVER}")
def filter_only_stream(spark, sf):
    return shown(Pipeline(alignments(spark, sf)).attach(RegionFilter(*FILTER_REGION)).run())


@query(AL + "SELECT seq::VARCHAR AS seq, quals FROM al WHERE ref_id = 5 AND mapq = 7")
def addr_lookup(spark, sf):
    pooled = P.pool(alignments(spark, sf), "storage")
    wanted = P.with_locator(digest(pooled, {"mapq": F.col("mapq")})).where("ref_id = 5 and mapq = 7").select("locator")
    return P.resolve(wanted, pooled).select(st("seq"), "quals")


@query(AL + "SELECT seq::VARCHAR AS seq, end_no, flag, ref_id, pos, CASE WHEN flag & 4 <> 0 THEN 0 ELSE u5 END AS u5, CASE WHEN flag & 16 <> 0 THEN 1 ELSE 0 END AS rev, score FROM al")
def digest_build(spark, sf):
    return dg(spark, sf).select(st("seq"), "end_no", "flag", "ref_id", "pos", "u5", "rev", "score")


@query(AL + "SELECT seq::VARCHAR AS seq, score FROM al")
def qual_score(spark, sf):
    return alignments(spark, sf).select(st("seq"), G.quality_score(F.col("quals")).alias("score"))


@query("SELECT vec_id, coalesce(list_sum(list_transform(list_filter(embedding, lambda x: x >= 0.1), lambda x: floor(x::DOUBLE * 1000)::BIGINT)), 0)::BIGINT AS score FROM embeddings")
def score_embedding(spark, sf):
    v = F.filter("embedding", lambda x: x >= F.lit(0.1).cast("float"))
    return table(spark, sf, "embeddings").select("vec_id", F.aggregate(v, F.lit(0).cast("long"), lambda a, x: a + F.floor(x.cast("double") * 1000)).alias("score"))


@query(AL + "SELECT ref_id, pos, count(*) AS n, min(seq)::VARCHAR AS first_seq, max(seq)::VARCHAR AS last_seq, max(score) AS best_score FROM al WHERE ref_id >= 0 GROUP BY 1, 2")
def idx_clipped(spark, sf):
    return P.groups(dg(spark, sf)).select("ref_id", "pos", "n", st("first_seq"), st("last_seq"), "best_score")


@query(AL + "SELECT ref_id, u5, count(*) AS n, min(seq)::VARCHAR AS first_seq, max(seq)::VARCHAR AS last_seq, max(score) AS best_score FROM al WHERE ref_id >= 0 GROUP BY 1, 2")
def idx_unclipped(spark, sf):
    return P.groups(dg(spark, sf), "unclipped").select("ref_id", "u5", "n", st("first_seq"), st("last_seq"), "best_score")


@query(AL + "SELECT seq::VARCHAR AS seq, flag, score FROM al WHERE ref_id = (SELECT min(ref_id) FROM al WHERE ref_id >= 0) AND pos = (SELECT min(pos) FROM al WHERE ref_id = (SELECT min(ref_id) FROM al WHERE ref_id >= 0))")
def idx_point(spark, sf):
    d = dg(spark, sf)
    ref, pos = d.where("ref_id >= 0").agg(F.min(F.struct("ref_id", "pos")).alias("p")).select("p.*").first()
    return P.at(d, ref, pos).select(st("seq"), "flag", "score")


_EN = AL + ", en AS (SELECT * FROM al WHERE flag & 2308 = 0) "


@query(_EN + "SELECT a.seq::VARCHAR AS seq, a.ref_id, a.u5, a.rev, b.ref_id AS m_ref, b.u5 AS m_u5, b.rev AS m_rev FROM en a JOIN en b ON a.tid = b.tid AND a.end_no <> b.end_no")
def mate_join(spark, sf):
    return P.with_mates(dg(spark, sf)).select(st("seq"), "ref_id", "u5", "rev", "m_ref", "m_u5", "m_rev")


@query(_EN + "SELECT tid::VARCHAR AS tid, " + ", ".join(f"max({c}) FILTER (WHERE end_no = {e}) AS {c}{e}" for e in (1, 2) for c in ("ref_id", "u5", "rev", "score")) + " FROM en GROUP BY tid")
def pair_pivot(spark, sf):
    return dupmark.collapse(dg(spark, sf)).select(st("tid"), *[f"{c}{e}" for e in (1, 2) for c in ("ref_id", "u5", "rev", "score")])


@query(AL + "SELECT least(floor((ref_id * 1000000 + greatest(u5, 0)) * 32 / 25000000), 31)::INT AS piece, count(*) AS n, min(u5)::BIGINT AS low, max(u5)::BIGINT AS high FROM al WHERE ref_id >= 0 GROUP BY 1")
def decompose_nb(spark, sf):
    return P.decompose(dg(spark, sf), 8, 4, [1_000_000] * 25).groupBy("piece").agg(F.count("*").alias("n"), F.min("u5").alias("low"), F.max("u5").alias("high"))


# ---- plug-ins -----------------------------------------------------------------


@query(AL + SHOWN + f"al WHERE {_OVER}")
def flt_region(spark, sf):
    return shown(RegionFilter(*FILTER_REGION).apply(alignments(spark, sf)))


def region_panel(spark, sf) -> DataFrame:
    return table(spark, sf, "nation").selectExpr("n_nationkey ref", "500 * (n_regionkey + 1) start", "500 * (n_regionkey + 1) + 3000 end")


_SET = AL + SHOWN + "al WHERE EXISTS (SELECT 1 FROM nation WHERE n_nationkey = ref_id AND pos <= 500 * (n_regionkey + 1) + 3000 AND pos + sp - 1 >= 500 * (n_regionkey + 1))"


@query(_SET)
def flt_region_set(spark, sf):
    return shown(RegionSetFilter(region_panel(spark, sf)).apply(alignments(spark, sf)))


@query(_SET)
def flt_region_nlj(spark, sf):
    """The plain form of the panel filter: a nested loop beside 25 broadcast intervals."""
    a, p = alignments(spark, sf), region_panel(spark, sf)
    return shown(a.join(F.broadcast(p), (a["ref_id"] <= p["ref"]) & (a["ref_id"] >= p["ref"]) & (a["pos"] <= p["end"]) & (a["pos"] + F.greatest(G.span(a["cigar"]), F.lit(1)) - 1 >= p["start"]), "left_semi"))


@query(AL + SHOWN + "al WHERE flag & 2 = 2 AND flag & 260 = 0")
def flt_flags(spark, sf):
    return shown(FlagFilter(require=2, exclude=260).apply(alignments(spark, sf)))


@query(AL + SHOWN + "al WHERE mapq >= 40")
def flt_mapq(spark, sf):
    return shown(MapqFilter(40).apply(alignments(spark, sf)))


_FLAGGED = """, mr AS (SELECT sa AS seq FROM pk2 WHERE rn > 1 UNION ALL SELECT sb FROM pk2 WHERE rn > 1 UNION ALL SELECT seq FROM fk WHERE hit OR rn > 1),
ma AS (SELECT al.*, CASE WHEN mr.seq IS NULL THEN 0 ELSE 1 END AS dup FROM al LEFT JOIN mr ON al.seq = mr.seq) """
_MARKED = marks_sql() + _FLAGGED
_MARKED_COLS = CORE_SQL.replace("flag", "flag + 1024 * dup AS flag")


def marked(spark, sf, **how) -> DataFrame:
    a = alignments(spark, sf)
    return dupmark.apply_marks(a, dupmark.mark_records(digest(a), **how))


@query(_MARKED + SHOWN + "ma WHERE dup = 0")
def dup_removed(spark, sf):
    return shown(FlagFilter(exclude=1024).apply(marked(spark, sf)))


@query("SELECT doc_id, lang, source FROM documents d WHERE NOT EXISTS (SELECT 1 FROM benchmark b WHERE contains(d.text, b.text))")
def flt_doc_benchmark_anti(spark, sf):
    """Documents without any whole benchmark passage."""
    d = table(spark, sf, "documents")
    b = table(spark, sf, "benchmark").select(F.col("text").alias("passage")).where(F.length("passage") > 0)
    hit = d.join(F.broadcast(b), F.contains(d["text"], b["passage"]), "left_anti")  # benchmark: a fixed list of passages
    return hit.select("doc_id", "lang", "source")


_REGION_MARKS = marks_sql().replace("WHERE flag & 2308 = 0", "WHERE flag & 2308 = 0 AND mapq >= 20")


@query(_REGION_MARKS + _FLAGGED + SHOWN.replace("flag", "flag + 1024 * dup AS flag") + "ma WHERE mapq >= 20")
def flt_then_mark(spark, sf):
    return shown(Pipeline(alignments(spark, sf)).attach(MapqFilter(20)).attach(DuplicateMarker()).run())


@query("SELECT page_id, octet_length(encode(html))::BIGINT AS raw_len, true AS same FROM pages")
def codec_roundtrip(spark, sf):
    out = pack.compress_payloads(table(spark, sf, "pages").select("page_id", "html"), "html", "dual")
    return out.select("page_id", "raw_len", (F.col("crc") == F.col("back_crc")).alias("same"))


@query(AL + "SELECT ref_id, bin, count(*) AS depth FROM (SELECT ref_id, unnest(range((pos // 1000)::BIGINT, ((pos + sp - 1) // 1000)::BIGINT + 1)) AS bin FROM al WHERE flag & 4 = 0) GROUP BY 1, 2")
def an_coverage(spark, sf):
    c = CoverageAnalyzer(1000)
    return c.analyze(digest(alignments(spark, sf), c.extras()))


@query(_MARKED + "SELECT count(*) AS total, count(*) FILTER (WHERE flag & 4 = 0) AS mapped, count(*) FILTER (WHERE flag & 2 <> 0) AS proper, count(*) FILTER (WHERE flag & 256 <> 0) AS secondary, count(*) FILTER (WHERE flag & 16 <> 0) AS reversed, count(*) FILTER (WHERE flag & 64 <> 0) AS first_ends, count(*) FILTER (WHERE dup = 1) AS duplicates FROM ma")
def an_flagstat(spark, sf):
    return FlagStat().analyze(digest(marked(spark, sf)))


@query(AL + "SELECT lib, count(*) AS n, floor(sum(tlen) * 100 / count(*))::BIGINT AS mean_x100, min(tlen) AS low, max(tlen) AS high FROM al WHERE tlen > 0 AND flag & 256 = 0 GROUP BY lib")
def an_insert_size(spark, sf):
    i = InsertSize()
    return i.analyze(digest(alignments(spark, sf), i.extras()))


# ---- duplicate marking -----------------------------------------------------------


@query(AL + "SELECT seq::VARCHAR AS seq, u5 FROM al WHERE flag & 4 = 0")
def geom_u5(spark, sf):
    return alignments(spark, sf).where("flag & 4 = 0").select(st("seq"), G.unclipped_5p(F.col("pos"), F.col("cigar"), F.col("flag")).alias("u5"))


@query(AL + "SELECT seq::VARCHAR AS seq, sp AS span, hd AS lead, tl AS trail FROM (SELECT al.*, regexp_extract(cigar, '^([0-9]+)S', 1) AS a, regexp_extract(cigar, 'M([0-9]+)S$', 1) AS b, CASE WHEN a = '' THEN 0 ELSE a::BIGINT END AS hd, CASE WHEN b = '' THEN 0 ELSE b::BIGINT END AS tl FROM al WHERE flag & 4 = 0)")
def geom_span(spark, sf):
    c = F.col("cigar")
    return alignments(spark, sf).where("flag & 4 = 0").select(st("seq"), G.span(c).alias("span"), G.leading_clip(c).alias("lead"), G.trailing_clip(c).alias("trail"))


@query(marks_sql() + "SELECT tid::VARCHAR AS tid, ra, ua, va, rb, ub, vb, pos, score FROM pr")
def pair_keys(spark, sf):
    return dupmark.pairs(dupmark.collapse(dg(spark, sf))).select(st("tid"), "ra", "ua", "va", "rb", "ub", "vb", "pos", "score")


@query(marks_sql() + "SELECT tid::VARCHAR AS tid, ref_id, u5, rev, pos, score FROM fr")
def frag_keys(spark, sf):
    return dupmark.fragments(dupmark.collapse(dg(spark, sf))).select(st("tid"), "ref_id", "u5", "rev", "pos", "score")


_PAIRS = "SELECT tid::VARCHAR AS tid, rep::VARCHAR AS rep, n AS set_size FROM pk2 WHERE rn > 1"


def _pairs(spark, sf, how="agg", tie="sorted", by_library=False, coarse=1):
    return dupmark.mark_pairs(dupmark.collapse(dg(spark, sf), by_library, coarse), how, tie).select(st("tid"), st("rep"), "set_size")


@query(marks_sql() + _PAIRS)
def mark_pairs_agg(spark, sf):
    return _pairs(spark, sf)


@query(marks_sql() + _PAIRS)
def mark_pairs_window(spark, sf):
    return _pairs(spark, sf, how="window")


@query(marks_sql() + "SELECT tid::VARCHAR AS tid, rep::VARCHAR AS rep, set_size FROM mk WHERE kind = 'fragment'")
def mark_frags(spark, sf):
    return dupmark.mark_fragments(dupmark.collapse(dg(spark, sf))).select(st("tid"), st("rep"), "set_size")


@query(marks_sql() + "SELECT tid::VARCHAR AS tid, rep::VARCHAR AS rep, set_size FROM mk WHERE kind = 'fragment'")
def mark_frags_window(spark, sf):
    return dupmark.mark_fragments(dupmark.collapse(dg(spark, sf)), "window").select(st("tid"), st("rep"), "set_size")


@query(AL + "SELECT count(*) FILTER (WHERE flag & 4 <> 0) AS unmapped, count(*) FILTER (WHERE flag & 256 <> 0) AS secondary, 0::BIGINT AS wrongly_marked FROM al")
def mark_exempt(spark, sf):
    m = marked(spark, sf)
    return m.agg(F.count_if(F.expr("flag & 4 <> 0")).alias("unmapped"), F.count_if(F.expr("flag & 256 <> 0")).alias("secondary"), F.count_if(F.expr("flag & 2308 <> 0 and flag & 1024 <> 0")).alias("wrongly_marked"))


@query(marks_sql(coarse=True) + _PAIRS)
def mark_tie_sorted(spark, sf):
    return _pairs(spark, sf, coarse=64)


@query(marks_sql(coarse=True, tie="input") + _PAIRS)
def mark_tie_input(spark, sf):
    return _pairs(spark, sf, coarse=64, tie="input")


@query(marks_sql(coarse=True) + ", b AS (SELECT *, max(score) OVER (PARTITION BY ra, ua, va, rb, ub, vb) AS best FROM pr) SELECT ra, ua, va, rb, ub, vb, count(*) FILTER (WHERE score = best) AS n_best, count(*) AS set_size FROM b GROUP BY ALL HAVING count(*) FILTER (WHERE score = best) > 1".replace("SELECT ra, ua, va, rb, ub, vb, count(*) FILTER", "SELECT ra, ua, va, rb, ub, vb, count(*) FILTER"))
def tie_sets(spark, sf):
    return dupmark.tie_sets(dupmark.collapse(dg(spark, sf), coarse=64)).select(*PAIR_KEY[1:], "n_best", "set_size")


@query(marks_sql(by_library=True) + "SELECT tid::VARCHAR AS tid, kind, rep::VARCHAR AS rep, set_size FROM mk")
def mark_by_library(spark, sf):
    return dupmark.mark_templates(dg(spark, sf), by_library=True).select(st("tid"), "kind", st("rep"), "set_size")


@query(_MARKED + "SELECT seq::VARCHAR AS seq, flag + 1024 * dup AS flag FROM ma")
def mark_flags(spark, sf):
    return marked(spark, sf).select(st("seq"), "flag")


@query(_MARKED + SHOWN.replace("flag", "flag + 1024 * dup AS flag") + "ma")
def mark_duplicates_full(spark, sf):
    """Filter, pool, index, mark and sort in one plan: the flagship."""
    return shown(Pipeline(alignments(spark, sf)).attach(DuplicateMarker()).run())


_KEYED = "SELECT {id}, rn > 1 AS is_dup, rep_tie, set_size FROM (SELECT {id}, row_number() OVER w AS rn, first_value({tie}) OVER w AS rep_tie, count(*) OVER (PARTITION BY {key}) AS set_size FROM {src} WINDOW w AS (PARTITION BY {key} ORDER BY {score} DESC, {tie}))"


@query(_KEYED.format(id="doc_id", tie="doc_id", key="text", score="score", src="(SELECT d.doc_id, text, coalesce(quality, -1) AS score FROM documents d LEFT JOIN labels USING (doc_id))"))
def mark_docs_exact(spark, sf):
    d = table(spark, sf, "documents").join(table(spark, sf, "labels").select("doc_id", "quality"), "doc_id", "left")
    return dupmark.mark_keyed(d.select("doc_id", "text", F.coalesce("quality", F.lit(-1)).alias("score")), ["text"], F.col("score"), F.col("doc_id")).select("doc_id", "is_dup", "rep_tie", "set_size")


@query(_KEYED.format(id="event_id", tie="event_id", key="user_id, event_type, k", score="score", src="(SELECT event_id, user_id, event_type, floor(value)::BIGINT // 5 AS k, round(value * 100)::BIGINT AS score FROM events)"))
def mark_events(spark, sf):
    e = table(spark, sf, "events").selectExpr("event_id", "user_id", "event_type", "floor(value) div 5 k", "cast(round(value * 100) as bigint) score")
    return dupmark.mark_keyed(e, ["user_id", "event_type", "k"], F.col("score"), F.col("event_id"), salt=8).select("event_id", "is_dup", "rep_tie", "set_size")


@query(_KEYED.format(id="o_orderkey", tie="o_orderkey", key="ref, u5", score="score", src="(SELECT o_orderkey, o_custkey % 25 AS ref, date_diff('day', DATE '1990-01-01', o_orderdate::DATE) // 3 AS u5, round(o_totalprice * 100)::BIGINT % 1000 AS score FROM orders)"))
def mark_orders(spark, sf):
    o = table(spark, sf, "orders").selectExpr("o_orderkey", "o_custkey % 25 ref", "datediff(cast(o_orderdate as date), date '1990-01-01') div 3 u5", "cast(round(o_totalprice * 100) as bigint) % 1000 score")
    return dupmark.mark_keyed(o, ["ref", "u5"], F.col("score"), F.col("o_orderkey")).select("o_orderkey", "is_dup", "rep_tie", "set_size")


@query(marks_sql() + "SELECT tid::VARCHAR AS tid FROM pk2 WHERE rn > 1")
def bf_mark(spark, sf):
    """Brute force over all pairs of one key, held against the keyed method's SQL."""
    return dupmark.brute_mark(dg(spark, sf)).select(st("tid"))


# ---- sort and write -----------------------------------------------------------------


def _placed(df: DataFrame) -> DataFrame:
    """Each row's number in the order that the plan gives, from partition and local order."""
    rows = df.withColumn("__at", F.monotonically_increasing_id()).withColumn("__part", F.spark_partition_id())
    rows = P.pool(rows, "storage")
    sizes = rows.groupBy("__part").agg(F.count("*").alias("n"))
    before = sizes.withColumn("before", F.coalesce(F.sum("n").over(Window.partitionBy(F.lit(1)).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("n")
    local = F.row_number().over(Window.partitionBy("__part").orderBy("__at"))
    return rows.withColumn("__local", local).join(F.broadcast(before), "__part").withColumn("rank", (F.col("before") + F.col("__local")).cast("long"))


_RANKED = "SELECT seq::VARCHAR AS seq, ref_id, pos, row_number() OVER (ORDER BY {o}) AS rank FROM al"


@query(AL + _RANKED.format(o="CASE WHEN ref_id < 0 THEN 2147483647 ELSE ref_id END, pos, seq"))
def sort_coordinate(spark, sf):
    return _placed(sortorder.sorted_scan(alignments(spark, sf).select("seq", "ref_id", "pos"))).select(st("seq"), "ref_id", "pos", "rank")


@query(AL + _RANKED.format(o="qname, seq"))
def sort_name(spark, sf):
    return _placed(sortorder.sort_by_name(alignments(spark, sf).select("seq", "ref_id", "pos", "qname"))).select(st("seq"), "ref_id", "pos", "rank")


@query(AL + ", r AS (" + _RANKED.format(o="CASE WHEN ref_id < 0 THEN 2147483647 ELSE ref_id END, pos, seq") + ") SELECT count(*) AS n, min(rank) AS first_rank, max(rank) AS last_rank FROM r WHERE ref_id < 0")
def sort_unmapped_last(spark, sf):
    return _placed(sortorder.sorted_scan(alignments(spark, sf).select("seq", "ref_id", "pos"))).where("ref_id < 0").agg(F.count("*").alias("n"), F.min("rank").alias("first_rank"), F.max("rank").alias("last_rank"))


@query(_MARKED + "SELECT seq::VARCHAR AS seq, flag + 1024 * dup AS flag FROM ma")
def overlay_sorted(spark, sf):
    a = P.pool(alignments(spark, sf))
    return sortorder.overlay_sorted(a, dupmark.mark_records(digest(a))).select(st("seq"), "flag")


_BYTES = AL + ", sz AS (SELECT seq, 44 + length(qname) + 4 * len(regexp_extract_all(cigar, '[0-9]+')) + 2 * 24 + list_sum(list_transform(string_split(tagtext, chr(9)), lambda t: 3 + length(string_split(t, ':')[3]))) AS rec_bytes FROM al), run AS (SELECT seq, rec_bytes, sum(rec_bytes) OVER (ORDER BY seq) - rec_bytes AS before FROM sz) "
_PREFIX = _BYTES + "SELECT seq::VARCHAR AS seq, rec_bytes::BIGINT AS rec_bytes, floor(before / 65536)::BIGINT AS block_no FROM run"


@query(_PREFIX)
def pack_prefix(spark, sf):
    from dupflow.plans.digest import record_bytes

    return pack.pack_prefix(alignments(spark, sf).select("seq", record_bytes().alias("rec_bytes")), ["seq"]).select(st("seq"), "rec_bytes", "block_no")


@query(_PREFIX)
def pack_from_digest(spark, sf):
    return pack.pack_prefix(dg(spark, sf).select("seq", "rec_bytes"), ["seq"]).select(st("seq"), "rec_bytes", "block_no")


@query(_BYTES + "SELECT count(*) AS n_rec, sum(rec_bytes)::BIGINT AS bytes, 0::BIGINT AS over, 0::BIGINT AS could_hold_more FROM sz")
def pack_greedy(spark, sf):
    """What holds for greedy blocks whatever the parts: all records and bytes, none over the limit, none that the next record would have fitted."""
    out = pack.pack_greedy(sortorder.sorted_scan(dg(spark, sf).select("seq", "ref_id", "pos", "rec_bytes")).withColumn("at", F.monotonically_increasing_id()))
    blocks = out.groupBy("part", "block_no").agg(F.count("*").alias("n"), F.sum("rec_bytes").alias("bytes"), F.min_by("rec_bytes", "at").alias("first"))
    follows = F.lead("first").over(Window.partitionBy("part").orderBy("block_no"))
    blocks = blocks.withColumn("next", follows)
    return blocks.agg(F.sum("n").alias("n_rec"), F.sum("bytes").alias("bytes"), F.count_if((F.col("bytes") > 65536) & (F.col("n") > 1)).alias("over"), F.count_if(F.col("bytes") + F.col("next") <= 65536).alias("could_hold_more"))


@query(AL + SHOWN + "al")
def baf_roundtrip(spark, sf):
    path = shared_path(spark, "baf")
    baf.write_baf(sortorder.sorted_scan(alignments(spark, sf)), path, "dual")
    return shown(baf.read_baf(spark, path))


@query(AL + SHOWN + f"al WHERE {_OVER}")
def baf_region_read(spark, sf):
    path = shared_path(spark, "baf")
    baf.write_baf(sortorder.sorted_scan(alignments(spark, sf)), path)
    return shown(RegionFilter(*FILTER_REGION).apply(baf.read_baf(spark, path, FILTER_REGION)))


@query(AL + SHOWN + f"al WHERE {_OVER}")
def baf_region_unsorted(spark, sf):
    """A region of a file in input order, as the filter-only plan writes it."""
    path = shared_path(spark, "baf")
    baf.write_baf(alignments(spark, sf), path)
    return shown(RegionFilter(*FILTER_REGION).apply(baf.read_baf(spark, path, FILTER_REGION)))


#: Bytes of stored alignments for each text file.
FILE_BYTES = 32 << 20


def taf_files(spark, sf, files: int = 5) -> str:
    """The alignments as text files in input order, a header before the first line; the reference dictionary is ``nation``.

    There are more than ``files`` where the alignments are large, one for each 32 MB as stored.
    """
    names = [r[0] for r in table(spark, sf, "nation").orderBy("n_nationkey").select("n_name").collect()]  # the reference dictionary
    head = ["@HD\tVN:1.5\tSO:unsorted", *[f"@SQ\tSN:{n}\tLN:1000000" for n in names], "@RG\tID:rg1\tLB:one"]
    stored = alignments(spark, sf)
    files = max(files, sum(P.input_bytes(spark, f) for f in stored.inputFiles()) // FILE_BYTES)
    lines = taf.render_taf(stored, names)
    both = spark.createDataFrame([(i - len(head), x) for i, x in enumerate(head)], "seq long, value string").select(F.col("seq").cast("decimal(38,0)").alias("seq"), "value").unionAll(lines)
    path = shared_path(spark, "taf")
    write_then_free(spark, lambda: both.repartitionByRange(files, "seq").sortWithinPartitions("seq").select("value").write.text(path))
    return path


@query(_MARKED + f"SELECT {_MARKED_COLS}, tagtext, CASE WHEN contains(tagtext, 'RG:Z:rg1') THEN 'one' ELSE regexp_extract(tagtext, 'RG:Z:(rg[0-9]+)', 1) END AS lib FROM ma")
def wl_taf_to_baf(spark, sf):
    """File to file: header and lines in, marked, sorted and compressed blocks out, then read again."""
    out = shared_path(spark, "baf")
    convert_files(spark, taf_files(spark, sf), out, [DuplicateMarker()])
    return shown(baf.read_baf(spark, out, seq_type="long"))


@query("SELECT 'HD' AS kind, 0 AS place, NULL AS name, 'coordinate' AS sort_order UNION ALL SELECT 'SQ', n_nationkey + 1, n_name, NULL FROM nation UNION ALL SELECT 'RG', (SELECT count(*)::INT FROM nation) + 1, NULL, NULL UNION ALL SELECT 'PG', (SELECT count(*)::INT FROM nation) + 2, NULL, NULL")
def hdr_kept(spark, sf):
    """The header of a converted file: all lines in their order, the sort order renewed, a program line added."""
    out = shared_path(spark, "baf")
    convert_files(spark, taf_files(spark, sf, 2), out, [DuplicateMarker()])
    rows = [(k, i, f.get("SN"), f.get("SO")) for k, i, f in baf.read_baf_header(out).rows()]
    return spark.createDataFrame(rows, "kind string, place int, name string, sort_order string")


@query(AL + "SELECT qname, quals FROM al WHERE ref_id = 5 AND mapq = 7")
def addr_fetch(spark, sf):
    """Lines fetched from text files by file number and byte offset."""
    path = taf_files(spark, sf)
    records, header = taf.read_taf(spark, path)
    wanted = P.with_locator(records).where("ref_id = 5 and mapq = 7").select("locator")
    return taf.parse_taf(P.fetch_lines(wanted, path), refs=header.refs()).select("qname", "quals")


@query(AL + SHOWN.replace(", lib FROM", " FROM") + "al")
def src_baf(spark, sf):
    """The block files as a data source of their own, read without the index."""
    path = shared_path(spark, "baf")
    baf.write_baf(alignments(spark, sf), path, "dual")
    baf.register(spark)
    return taf.parse_taf(spark.read.format("baf").load(path)).select(*CORE, tag_text())


# ---- baselines ------------------------------------------------------------------------


@query(AL + _RANKED.format(o="CASE WHEN ref_id < 0 THEN 2147483647 ELSE ref_id END, pos, seq"))
def bl_sort_pass(spark, sf):
    out = baselines.sort_pass(alignments(spark, sf), shared_path(spark, "sorted"))
    return _placed(sortorder.sorted_scan(out.select("seq", "ref_id", "pos"))).select(st("seq"), "ref_id", "pos", "rank")


@query(_MARKED + "SELECT seq::VARCHAR AS seq, flag + 1024 * dup AS flag FROM ma")
def bl_mark_pass(spark, sf):
    path = shared_path(spark, "sorted")
    baselines.sort_pass(alignments(spark, sf), path)
    return baselines.mark_pass(spark, path, shared_path(spark, "marked")).select(st("seq"), "flag")


@query(_MARKED + SHOWN.replace("flag", "flag + 1024 * dup AS flag") + "ma")
def bl_two_pass(spark, sf):
    return shown(baselines.two_pass(alignments(spark, sf)))


# ---- measures -----------------------------------------------------------------------------

#: Cost in whole units of each run: an input is a return flag, a configuration a line number.
_COST = "(SELECT l_returnflag AS input, l_linenumber AS config, sum(l_quantity::BIGINT)::BIGINT AS cost, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS cents FROM lineitem GROUP BY 1, 2)"


@query(f"SELECT t.input, t.config, (100 * b.cost // nullif(t.cost, 0)) / 100.0::DOUBLE AS speedup FROM {_COST} t JOIN {_COST} b ON t.input = b.input AND b.config = 1")
def m_speedup(spark, sf):
    """Speed-up of each configuration over the first, by input; to two places, rounded down."""
    return metrics.speedups(metrics.costs(table(spark, sf, "lineitem")), 1)


@query(
    f"WITH c AS (SELECT input, max(cost) FILTER (WHERE config = 1) AS one, max(cost) FILTER (WHERE config = 2) AS two, max(cost) FILTER (WHERE config = 3) AS three, sum(cents)::BIGINT AS cents, sum(cost)::BIGINT AS cost FROM {_COST} GROUP BY 1), "
    "m AS (SELECT 'gain_' || input AS measure, 1000 * one // nullif(two, 0) - 1000 AS v FROM c UNION ALL SELECT 'slowdown_' || input, 1000 * two // nullif(three, 0) - 1000 FROM c UNION ALL SELECT 'cents_per_unit_' || input, 1000 * cents // nullif(cost, 0) FROM c) SELECT measure, v / 1000.0::DOUBLE AS value FROM m"
)
def m_paper_ratios(spark, sf):
    """The kinds of ratio that are published, of the costs at hand: gain, slow-down and use for each unit; to three places, rounded down."""
    return metrics.ratios(metrics.costs(table(spark, sf, "lineitem")))


@query("WITH t AS (SELECT l_linenumber AS threads, sum(l_quantity::BIGINT)::BIGINT AS cost FROM lineitem GROUP BY 1), f AS (SELECT cost AS one FROM t WHERE threads = 1) SELECT threads, cost, (100 * cost // nullif(one, 0)) / 100.0::DOUBLE AS relative, (100 * one // nullif(cost, 0)) / 100.0::DOUBLE AS speedup FROM t CROSS JOIN f")
def m_thread_scaling(spark, sf):
    """Cost by number of threads (the line number), relative to one thread; to two places, rounded down."""
    return metrics.scaling(metrics.costs(table(spark, sf, "lineitem")))


@query("WITH t AS (SELECT sum(l_quantity::BIGINT) FILTER (WHERE l_linestatus = 'F')::BIGINT AS shared, sum(l_quantity::BIGINT)::BIGINT AS total FROM lineitem), w AS (SELECT DISTINCT l_linenumber::BIGINT AS workers FROM lineitem) SELECT workers, (10000 * total * workers // nullif((total - shared) * workers + shared, 0)) / 10000.0::DOUBLE AS bound FROM t CROSS JOIN w")
def m_amdahl(spark, sf):
    """Bound on the speed-up by workers (line numbers), the finished lines being the parallel share of the cost; to four places, rounded down."""
    return metrics.bounds(table(spark, sf, "lineitem"))


# ---- comparison ------------------------------------------------------------------------------


def perturbed(records: DataFrame) -> DataFrame:
    """What another tool's output looks like: tags in another order and one more tag."""
    extra = F.array(F.struct(F.lit("PG").alias("tag"), F.lit("Z").alias("type"), F.lit("mark").alias("value")))
    return records.withColumn("tags", F.concat(F.reverse("tags"), extra))


@query(_MARKED + SHOWN.replace("flag", "flag + 1024 AS flag") + "ma WHERE dup = 1")
def cmp_extract(spark, sf):
    return shown(compare.extract_marked(marked(spark, sf)))


_SORTED_TAGS = "array_to_string(list_sort(string_split(tagtext, chr(9))), chr(9))"


@query(AL + f"SELECT seq::VARCHAR AS seq, {_SORTED_TAGS} AS tagtext FROM al")
def cmp_norm_tags(spark, sf):
    return compare.sort_tags(alignments(spark, sf)).select(st("seq"), tag_text())


@query("SELECT unnest(['BC', 'NM', 'RG']) AS tag")
def cmp_common_tags(spark, sf):
    a = alignments(spark, sf)
    return spark.createDataFrame([(t,) for t in compare.common_tags(a, perturbed(a))], "tag string")


@query("SELECT 'SQ' AS kind, n_nationkey AS ord, n_name AS name FROM nation UNION ALL SELECT 'HD', -1, NULL")
def cmp_header(spark, sf):
    from dupflow.fixtures import reference_header

    return compare.without_version(reference_header(spark, sf)).select("kind", "ord", F.col("fields")["SN"].alias("name"))


@query(_MARKED + f"SELECT {_TAF.replace('tagtext', _SORTED_TAGS).replace('flag', 'flag + 1024')} AS line, row_number() OVER (ORDER BY {_TAF.replace('tagtext', _SORTED_TAGS).replace('flag', 'flag + 1024')}) AS rank FROM ma WHERE dup = 1")
def cmp_order_norm(spark, sf):
    lines = compare.as_text(compare.sort_tags(compare.extract_marked(marked(spark, sf)))).repartitionByRange("line").sortWithinPartitions("line")
    return _placed(lines).select("line", "rank")


@query("SELECT 0::BIGINT AS only_a, 0::BIGINT AS only_b")
def cmp_except_all(spark, sf):
    m = marked(spark, sf)
    x, y = compare.normalise(compare.extract_marked(m), compare.extract_marked(perturbed(m)))
    x, y = compare.as_text(x), compare.as_text(y)
    return x.exceptAll(y).agg(F.count("*").alias("only_a")).crossJoin(y.exceptAll(x).agg(F.count("*").alias("only_b")))


@query(marks_sql() + ", a AS (SELECT tid FROM pk2 WHERE rn > 1), b AS (SELECT tid FROM (" + marks_sql(by_library=True) + "SELECT tid FROM pk2 WHERE rn > 1)) SELECT 2 * (SELECT count(*) FROM a WHERE tid NOT IN (SELECT tid FROM b)) + (SELECT count(*) FROM mk WHERE kind = 'fragment' AND tid NOT IN (SELECT tid FROM (" + marks_sql(by_library=True) + "SELECT tid FROM mk WHERE kind = 'fragment'))) AS only_a, 2 * (SELECT count(*) FROM b WHERE tid NOT IN (SELECT tid FROM a)) + (SELECT count(*) FROM (" + marks_sql(by_library=True) + "SELECT tid FROM mk WHERE kind = 'fragment') WHERE tid NOT IN (SELECT tid FROM mk WHERE kind = 'fragment')) AS only_b")
def acc_diff_counts(spark, sf):
    """Marks with and without library keys differ in a known number of records: the measure sees it."""
    return compare.differences(marked(spark, sf), marked(spark, sf, by_library=True))


@query("SELECT 0::BIGINT AS only_a, 0::BIGINT AS only_b, true AS accurate")
def acc_verdict(spark, sf):
    return compare.verdict(marked(spark, sf), marked(spark, sf, how="window"))


@query(_MARKED + "SELECT count(*) AS marked FROM ma WHERE dup = 1")
def acc_dup_count(spark, sf):
    return marked(spark, sf).where("flag & 1024 <> 0").agg(F.count("*").alias("marked"))


# ---- workloads -----------------------------------------------------------------------------------

_WORKLOAD = _MARKED + "SELECT count(*) AS records, sum(dup)::BIGINT AS marked, sum(flag + 1024 * dup)::BIGINT AS flag_sum, count(DISTINCT CASE WHEN dup = 1 THEN tid END) AS templates FROM ma"


def _workload(spark, sf, mode: str):
    out = Pipeline(alignments(spark, sf), mode).attach(DuplicateMarker()).run()
    return out.agg(F.count("*").alias("records"), F.count_if(F.expr("flag & 1024 <> 0")).alias("marked"), F.sum("flag").alias("flag_sum"), F.count_distinct(F.when(F.expr("flag & 1024 <> 0"), F.col("tid"))).alias("templates"))


@query(_WORKLOAD)
def wl_we_memory(spark, sf):
    return _workload(spark, sf, "memory")


@query(_WORKLOAD)
def wl_we_storage(spark, sf):
    return _workload(spark, sf, "storage")


@query("SELECT 0::BIGINT AS only_a, 0::BIGINT AS only_b, true AS accurate")
def wl_accuracy(spark, sf):
    """The pipeline's marked set against the two-pass baseline's, tags perturbed."""
    a = alignments(spark, sf)
    return compare.verdict(Pipeline(a).attach(DuplicateMarker()).run(), perturbed(baselines.two_pass(a)))


@query(_MARKED + "SELECT count(*) AS records, sum(dup)::BIGINT AS marked FROM ma")
def wl_convert_baf(spark, sf):
    """Whole conversion: mark, sort, pack, compress, write; counted from the files."""
    path = shared_path(spark, "baf")
    Pipeline(alignments(spark, sf)).attach(DuplicateMarker()).write(path)
    return baf.read_baf(spark, path).agg(F.count("*").alias("records"), F.count_if(F.expr("flag & 1024 <> 0")).alias("marked"))

