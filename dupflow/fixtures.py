"""Alignments derived from ``lineitem`` by whole-number expressions, as Spark and as SQL.

Each row is a template with a left and a right end and sometimes a secondary
line; the rules are those of FIXTURES.md.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dupflow.registry import table
from dupflow.schema import RECORD
from dupflow.shared import exists, shared_path, write_then_free

READ_BASES = 24


def templates(spark: SparkSession, sf_dir: str, files: int = 16) -> DataFrame:
    """One row for each template with the numbers that its records come from."""
    t = table(spark, sf_dir, "lineitem").repartitionByRange(files, "l_orderkey").selectExpr(
        "l_orderkey ok", "cast(l_linenumber as bigint) ln", "l_partkey pk", "l_suppkey sk", "cast(round(l_extendedprice * 100) as bigint) cents", "cast(l_quantity as bigint) q",
        "cast(round(l_discount * 100) as bigint) dsc", "cast(round(l_tax * 100) as bigint) tx", "l_returnflag lib", "l_linestatus = 'F' right_rev",
    )
    t = t.selectExpr(
        "*", "ln % 4 hd", "tx % 3 tl", "24 - ln % 4 - tx % 3 c", "case when dsc = 9 then 'U' when dsc = 10 then 'F' else 'P' end kind",
        "cast(ok as decimal(38,0)) * 10000000000000000000000000BD + cast(ln * 100000000 + pk as decimal(38,0)) * 10000000000000000BD + cast(sk as decimal(38,0)) * 1000000000BD + cents tid",
    )
    return t.selectExpr(
        "*",
        "case when q % 10 = 0 then concat('8M1I', c - 9, 'M') when q % 10 = 1 then concat('8M2D', c - 8, 'M') else concat(c, 'M') end core",
        "case when q % 10 = 0 then c - 1 when q % 10 = 1 then c + 2 else c end sp",
        "sk % 25 lref", "case when dsc = 8 then (sk + 1) % 25 else sk % 25 end rref", "100 + 7 * pk lu5", "250 + 7 * pk + 50 * (q % 3) ru5",
        "kind <> 'U' lmap", "kind = 'P' rmap", "concat_ws(':', ok, ln, pk, sk, cents) qname", "case when q % 2 = 0 then 2 else 1 end lend",
    )


_STORED: dict[tuple[str, str], str] = {}


def alignments(spark: SparkSession, sf_dir: str, files: int = 16) -> DataFrame:
    """The records of all templates, derived once a session and table, stored in ``files`` files and read from there."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _STORED or not exists(spark, _STORED[key]):
        path = shared_path(spark, "alignments")
        write_then_free(spark, lambda: derived_alignments(spark, sf_dir, files).write.option("compression", "zstd").parquet(path))
        _STORED[key] = path
    return spark.read.parquet(_STORED[key])


def derived_alignments(spark: SparkSession, sf_dir: str, files: int = 16) -> DataFrame:
    """The records of all templates, from ``lineitem``, dealt by order so that no task derives them alone."""
    t = templates(spark, sf_dir, files).selectExpr(
        "*", "concat(case when hd > 0 then concat(hd, 'S') else '' end, core, case when tl > 0 then concat(tl, 'S') else '' end) cig",
        "lu5 + hd lpos", "case when right_rev then ru5 - tl - sp + 1 else ru5 + hd end rpos",
        "array_join(transform(sequence(0, 23), i -> substr('ACGT', cast(1 + (pk + i) % 4 as int), 1)), '') bases",
        "case when q % 10 = 0 then 1 when q % 10 = 1 then 2 else 0 end nm",
    )
    quals = "array_join(transform(sequence(0, 23), i -> char(33 + (cents * (i + {o}) + pk * 7 + i * i) % 41)), '')"
    t = t.selectExpr(
        "*", "case when kind = 'P' and lref = rref then greatest(lpos, rpos) + sp - least(lpos, rpos) else 0 end ins",
        "case ln % 3 when 0 then array(named_struct('tag', 'NM', 'type', 'i', 'value', cast(nm as string)), named_struct('tag', 'RG', 'type', 'Z', 'value', concat('rg', ln)), named_struct('tag', 'BC', 'type', 'Z', 'value', lib))"
        " when 1 then array(named_struct('tag', 'RG', 'type', 'Z', 'value', concat('rg', ln)), named_struct('tag', 'BC', 'type', 'Z', 'value', lib), named_struct('tag', 'NM', 'type', 'i', 'value', cast(nm as string)))"
        " else array(named_struct('tag', 'BC', 'type', 'Z', 'value', lib), named_struct('tag', 'NM', 'type', 'i', 'value', cast(nm as string)), named_struct('tag', 'RG', 'type', 'Z', 'value', concat('rg', ln))) end tags",
    )
    proper = "case when kind = 'P' and lref = rref and right_rev then 2 else 0 end"
    left = (
        f"named_struct('part', 0, 'flag', cast(1 + {proper} + if(lmap, 0, 4) + if(rmap, 0, 8) + if(rmap and right_rev, 32, 0) + if(lend = 1, 64, 128) as int), 'ref_id', cast(if(lmap, lref, -1) as int), 'pos', if(lmap, lpos, 0L), 'cigar', if(lmap, cig, '*'),"
        f" 'mate_ref_id', cast(if(rmap, rref, -1) as int), 'mate_pos', if(rmap, rpos, 0L), 'tlen', if(lpos <= rpos, ins, -ins), 'quals', {quals.format(o=3)})"
    )
    right = (
        f"named_struct('part', 1, 'flag', cast(1 + {proper} + if(rmap, 0, 4) + if(lmap, 0, 8) + if(rmap and right_rev, 16, 0) + if(lend = 1, 128, 64) as int), 'ref_id', cast(if(rmap, rref, -1) as int), 'pos', if(rmap, rpos, 0L), 'cigar', if(rmap, cig, '*'),"
        f" 'mate_ref_id', cast(if(lmap, lref, -1) as int), 'mate_pos', if(lmap, lpos, 0L), 'tlen', if(lpos <= rpos, -ins, ins), 'quals', {quals.format(o=11)})"
    )
    second = left.replace("'part', 0", "'part', 2").replace("as int), 'ref_id'", "as int) + 256, 'ref_id'").replace("if(lmap, lpos, 0L), 'cigar'", "1100 + 7 * pk + hd, 'cigar'")
    t = t.selectExpr("*", f"explode(if(q = 50 and kind = 'P', array({left}, {right}, {second}), array({left}, {right}))) r")
    return t.selectExpr(
        "cast(tid * 10 + r.part as decimal(38,0)) seq", "cast(tid as decimal(38,0)) tid", "qname", "r.flag", "r.ref_id", "r.pos", "cast((pk + ln) % 61 as int) mapq", "r.cigar", "r.mate_ref_id", "r.mate_pos", "r.tlen", "bases", "r.quals", "tags", "lib",
    ).select(*RECORD)


def reference_header(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The reference dictionary from ``nation``: name and length of each reference id."""
    return table(spark, sf_dir, "nation").selectExpr("'SQ' kind", "n_nationkey ord", "map('SN', n_name, 'LN', '1000000') fields").unionAll(spark.sql("SELECT 'HD' kind, -1 ord, map('VN', '1.5', 'SO', 'unsorted') fields"))


#: DuckDB twin of :func:`alignments`: common table expressions that end in ``al``.
AL = r"""WITH tp AS (
  SELECT *, ln % 4 AS hd, tx % 3 AS tl, 24 - ln % 4 - tx % 3 AS c, CASE WHEN dsc = 9 THEN 'U' WHEN dsc = 10 THEN 'F' ELSE 'P' END AS kind,
    ok::HUGEINT * 10000000000000000000000000 + (ln * 100000000 + pk)::HUGEINT * 10000000000000000 + sk::HUGEINT * 1000000000 + cents AS tid
  FROM (SELECT l_orderkey AS ok, l_linenumber::BIGINT AS ln, l_partkey AS pk, l_suppkey AS sk, round(l_extendedprice * 100)::BIGINT AS cents, l_quantity::BIGINT AS q,
    round(l_discount * 100)::BIGINT AS dsc, round(l_tax * 100)::BIGINT AS tx, l_returnflag AS lib, l_linestatus = 'F' AS rrev FROM lineitem)
), tq AS (
  SELECT *, CASE WHEN q % 10 = 0 THEN '8M1I' || (c - 9) || 'M' WHEN q % 10 = 1 THEN '8M2D' || (c - 8) || 'M' ELSE c || 'M' END AS core,
    CASE WHEN q % 10 = 0 THEN c - 1 WHEN q % 10 = 1 THEN c + 2 ELSE c END AS sp, sk % 25 AS lref, CASE WHEN dsc = 8 THEN (sk + 1) % 25 ELSE sk % 25 END AS rref,
    100 + 7 * pk AS lu5, 250 + 7 * pk + 50 * (q % 3) AS ru5, kind <> 'U' AS lmap, kind = 'P' AS rmap, ok || ':' || ln || ':' || pk || ':' || sk || ':' || cents AS qname
  FROM tp
), tr AS (
  SELECT *, CASE WHEN hd > 0 THEN hd || 'S' ELSE '' END || core || CASE WHEN tl > 0 THEN tl || 'S' ELSE '' END AS cig, lu5 + hd AS lpos,
    CASE WHEN rrev THEN ru5 - tl - sp + 1 ELSE ru5 + hd END AS rpos, CASE WHEN q % 10 = 0 THEN 1 WHEN q % 10 = 1 THEN 2 ELSE 0 END AS nm,
    array_to_string(list_transform(range(24), lambda i: substr('ACGT', (1 + (pk + i) % 4)::INT, 1)), '') AS bases FROM tq
), ts AS (
  SELECT *, CASE WHEN kind = 'P' AND lref = rref THEN greatest(lpos, rpos) + sp - least(lpos, rpos) ELSE 0 END AS ins,
    CASE WHEN kind = 'P' AND lref = rref AND rrev THEN 2 ELSE 0 END AS proper,
    CASE ln % 3 WHEN 0 THEN 'NM:i:' || nm || chr(9) || 'RG:Z:rg' || ln || chr(9) || 'BC:Z:' || lib WHEN 1 THEN 'RG:Z:rg' || ln || chr(9) || 'BC:Z:' || lib || chr(9) || 'NM:i:' || nm
      ELSE 'BC:Z:' || lib || chr(9) || 'NM:i:' || nm || chr(9) || 'RG:Z:rg' || ln END AS tagtext FROM tr
), al AS MATERIALIZED (
  SELECT tid * 10 + part AS seq, tid, qname, flag::INT AS flag, ref_id::INT AS ref_id, pos, ((pk + ln) % 61)::INT AS mapq, cigar, mate_ref_id::INT AS mate_ref_id, mate_pos, tlen, bases,
    array_to_string(list_transform(range(24), lambda i: chr((33 + (cents * (i + o) + pk * 7 + i * i) % 41)::INT)), '') AS quals, tagtext, lib, u5, rev,
    list_sum(list_transform(range(24), lambda i: CASE WHEN (cents * (i + o) + pk * 7 + i * i) % 41 >= 15 THEN (cents * (i + o) + pk * 7 + i * i) % 41 ELSE 0 END))::BIGINT AS score, sp,
    CASE WHEN flag & 64 <> 0 THEN 1 ELSE 2 END AS end_no, kind
  FROM (
    SELECT *, 0 AS part, 3 AS o, 1 + proper + CASE WHEN lmap THEN 0 ELSE 4 END + CASE WHEN rmap THEN 0 ELSE 8 END + CASE WHEN rmap AND rrev THEN 32 ELSE 0 END + CASE WHEN q % 2 = 1 THEN 64 ELSE 128 END AS flag,
      CASE WHEN lmap THEN lref ELSE -1 END AS ref_id, CASE WHEN lmap THEN lpos ELSE 0 END AS pos, CASE WHEN lmap THEN cig ELSE '*' END AS cigar, CASE WHEN rmap THEN rref ELSE -1 END AS mate_ref_id,
      CASE WHEN rmap THEN rpos ELSE 0 END AS mate_pos, CASE WHEN lpos <= rpos THEN ins ELSE -ins END AS tlen, lu5 AS u5, 0 AS rev FROM ts
    UNION ALL
    SELECT *, 1, 11, 1 + proper + CASE WHEN rmap THEN 0 ELSE 4 END + CASE WHEN lmap THEN 0 ELSE 8 END + CASE WHEN rmap AND rrev THEN 16 ELSE 0 END + CASE WHEN q % 2 = 1 THEN 128 ELSE 64 END,
      CASE WHEN rmap THEN rref ELSE -1 END, CASE WHEN rmap THEN rpos ELSE 0 END, CASE WHEN rmap THEN cig ELSE '*' END, CASE WHEN lmap THEN lref ELSE -1 END,
      CASE WHEN lmap THEN lpos ELSE 0 END, CASE WHEN lpos <= rpos THEN -ins ELSE ins END, ru5, CASE WHEN rrev THEN 1 ELSE 0 END FROM ts
    UNION ALL
    SELECT *, 2, 3, 257 + proper + CASE WHEN rrev THEN 32 ELSE 0 END + CASE WHEN q % 2 = 1 THEN 64 ELSE 128 END, lref, 1100 + 7 * pk + hd, cig, rref, rpos, CASE WHEN lpos <= rpos THEN ins ELSE -ins END, 1100 + 7 * pk, 0
      FROM ts WHERE q = 50 AND kind = 'P'
  )
)
"""

#: Adds the primary mapped ends, pairs and fragments to :data:`AL`; ``{lib}`` is the library part of keys.
MARKS = AL + r""", e1 AS (SELECT tid, lib, ref_id, u5, rev, pos, score, seq, row_number() OVER (PARTITION BY tid ORDER BY ref_id, u5, rev, end_no) AS k FROM al WHERE flag & 2308 = 0),
e2 AS MATERIALIZED (SELECT tid, any_value(lib) AS lib, count(*) AS ends, sum(score)::BIGINT AS total,
  any_value(ref_id) FILTER (WHERE k = 1) AS ra, any_value(u5) FILTER (WHERE k = 1) AS ua, any_value(rev) FILTER (WHERE k = 1) AS va, any_value(pos) FILTER (WHERE k = 1) AS pos, any_value(seq) FILTER (WHERE k = 1) AS sa,
  any_value(ref_id) FILTER (WHERE k = 2) AS rb, any_value(u5) FILTER (WHERE k = 2) AS ub, any_value(rev) FILTER (WHERE k = 2) AS vb, any_value(seq) FILTER (WHERE k = 2) AS sb FROM e1 GROUP BY tid),
pr AS (SELECT tid, {lib} AS klib, ra, ua, va, rb, ub, vb, pos, {score} AS score, sa, sb FROM e2 WHERE ends = 2),
fr AS (SELECT tid, {lib} AS klib, ra AS ref_id, ua AS u5, va AS rev, pos, {score} AS score, sa AS seq FROM e2 WHERE ends = 1),
pk2 AS MATERIALIZED (SELECT *, row_number() OVER w AS rn, count(*) OVER (PARTITION BY klib, ra, ua, va, rb, ub, vb) AS n, first_value(tid) OVER w AS rep FROM pr WINDOW w AS (PARTITION BY klib, ra, ua, va, rb, ub, vb ORDER BY score DESC, {tie} tid)),
pe AS (SELECT klib, ra AS ref_id, ua AS u5, va AS rev FROM pr UNION SELECT klib, rb, ub, vb FROM pr),
fk AS MATERIALIZED (SELECT f.*, row_number() OVER w AS rn, count(*) OVER (PARTITION BY f.klib, f.ref_id, f.u5, f.rev) AS n, first_value(tid) OVER w AS rep, pe.u5 IS NOT NULL AS hit
  FROM fr f LEFT JOIN pe ON f.klib = pe.klib AND f.ref_id = pe.ref_id AND f.u5 = pe.u5 AND f.rev = pe.rev WINDOW w AS (PARTITION BY f.klib, f.ref_id, f.u5, f.rev ORDER BY f.score DESC, {ftie} f.tid)),
mk AS (SELECT tid, 'pair' AS kind, rep, n AS set_size FROM pk2 WHERE rn > 1 UNION ALL SELECT tid, 'fragment', CASE WHEN hit THEN NULL ELSE rep END, n FROM fk WHERE hit OR rn > 1)
"""


def marks_sql(by_library: bool = False, tie: str = "sorted", coarse: bool = False) -> str:
    """:data:`MARKS` for the given options."""
    return MARKS.format(lib="lib" if by_library else "''", score="total // 64" if coarse else "total", tie="pos," if tie == "sorted" else "", ftie="f.pos," if tie == "sorted" else "")
