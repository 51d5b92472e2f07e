"""General relational operators around the methods, on the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from dupflow.fixtures import AL, alignments
from dupflow.functions.geometry import cigar_ops
from dupflow.plans.digest import digest
from dupflow.registry import query, table
from dupflow.shared import shared_path


def line(spark, sf):
    return table(spark, sf, "lineitem").withColumn("cents", F.expr("cast(round(l_extendedprice * 100) as bigint)"))


LI = "(SELECT *, round(l_extendedprice * 100)::BIGINT AS cents FROM lineitem)"

# ---- scans, projections, filters -----------------------------------------------


@query("SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_returnflag FROM lineitem")
def scan_parquet(spark, sf):
    return table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag")


@query("SELECT l_partkey, l_quantity FROM lineitem WHERE l_quantity >= 45")
def scan_pruned(spark, sf):
    return table(spark, sf, "lineitem").where("l_quantity >= 45").select("l_partkey", "l_quantity")


@query("SELECT l_orderkey AS k, l_linenumber + 1 AS n, upper(l_returnflag) AS flag, CASE WHEN l_tax > 0.05 THEN 'high' ELSE 'low' END AS tax FROM lineitem")
def prj_basic(spark, sf):
    return table(spark, sf, "lineitem").select(F.col("l_orderkey").alias("k"), (F.col("l_linenumber") + 1).alias("n"), F.upper("l_returnflag").alias("flag"), F.when(F.col("l_tax") > 0.05, "high").otherwise("low").alias("tax"))


@query(AL + "SELECT seq::VARCHAR AS seq, ref_id, pos, end_no FROM al")
def prj_struct(spark, sf):
    a = digest(alignments(spark, sf)).withColumn("place", F.struct("ref_id", "pos"))
    return a.select(F.col("seq").cast("string").alias("seq"), "place.*", "end_no")


@query("SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity BETWEEN 10 AND 12")
def flt_between(spark, sf):
    return table(spark, sf, "lineitem").where(F.col("l_quantity").between(10, 12)).select("l_orderkey", "l_partkey")


@query("SELECT p_partkey, p_size FROM part WHERE p_size IN (1, 7, 49) AND p_brand NOT IN ('Brand#11')")
def flt_in(spark, sf):
    return table(spark, sf, "part").where(F.col("p_size").isin(1, 7, 49) & ~F.col("p_brand").isin("Brand#11")).select("p_partkey", "p_size")


@query("SELECT p_partkey, p_type FROM part WHERE p_type LIKE '%E%' OR regexp_matches(p_name, '^[a-p]')")
def flt_like(spark, sf):
    return table(spark, sf, "part").where(F.col("p_type").like("%E%") | F.col("p_name").rlike("^[a-p]")).select("p_partkey", "p_type")


@query("SELECT d.doc_id, quality IS NULL AS unlabelled FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE quality IS NULL OR toxic IS NOT NULL")
def flt_null(spark, sf):
    d, lab = table(spark, sf, "documents").select("doc_id"), table(spark, sf, "labels")
    return d.join(lab, "doc_id", "left").where(F.col("quality").isNull() | F.col("toxic").isNotNull()).select("doc_id", F.col("quality").isNull().alias("unlabelled"))


@query(AL + "SELECT seq::VARCHAR AS seq, flag FROM al WHERE flag & 16 <> 0 AND flag & 4 = 0")
def flt_bits(spark, sf):
    return alignments(spark, sf).where("flag & 16 <> 0 and flag & 4 = 0").select(F.col("seq").cast("string").alias("seq"), "flag")


# ---- joins -------------------------------------------------------------------------

_JN = "SELECT l_orderkey, l_linenumber, l_partkey, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_quantity > 40"


def _jn(spark, sf, hint=None):
    left = table(spark, sf, "lineitem").where("l_quantity > 40").select("l_orderkey", "l_linenumber", "l_partkey")
    o = table(spark, sf, "orders").select("o_orderkey", "o_custkey")
    o = o.hint(hint) if hint else o
    return left.join(o, left["l_orderkey"] == o["o_orderkey"]).drop("o_orderkey")


@query("SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def jn_bhj(spark, sf):
    s, n, r = (table(spark, sf, t) for t in ("supplier", "nation", "region"))
    return s.join(F.broadcast(n), s["s_nationkey"] == n["n_nationkey"]).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select("s_suppkey", "n_name", "r_name")


@query(_JN)
def jn_shj(spark, sf):
    return _jn(spark, sf, "shuffle_hash")


@query(_JN)
def jn_smj(spark, sf):
    return _jn(spark, sf, "merge")


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def jn_left(spark, sf):
    c, o = table(spark, sf, "customer").select("c_custkey"), table(spark, sf, "orders").select("o_custkey", "o_orderkey")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("SELECT c_custkey, s_suppkey FROM customer FULL JOIN supplier ON c_custkey = s_suppkey * 20")
def jn_full(spark, sf):
    c, s = table(spark, sf, "customer").select("c_custkey"), table(spark, sf, "supplier").select("s_suppkey")
    return c.join(s, c["c_custkey"] == s["s_suppkey"] * 20, "full")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity = 50)")
def jn_semi(spark, sf):
    big = table(spark, sf, "lineitem").where("l_quantity = 50").select(F.col("l_orderkey").alias("o_orderkey"))
    return table(spark, sf, "orders").select("o_orderkey").join(big, "o_orderkey", "left_semi")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R')")
def jn_anti(spark, sf):
    returned = table(spark, sf, "lineitem").where("l_returnflag = 'R'").select(F.col("l_orderkey").alias("o_orderkey"))
    return table(spark, sf, "orders").select("o_orderkey").join(returned, "o_orderkey", "left_anti")


@query("SELECT r_regionkey, n_nationkey FROM region, nation WHERE n_regionkey > r_regionkey")
def jn_theta(spark, sf):
    r, n = table(spark, sf, "region"), table(spark, sf, "nation")
    return n.join(F.broadcast(r), n["n_regionkey"] > r["r_regionkey"]).select("r_regionkey", "n_nationkey")


_RANGE = AL + "SELECT n_nationkey AS panel, count(*) AS n FROM al JOIN nation ON n_nationkey = ref_id AND pos <= 500 * (n_regionkey + 1) + 3000 AND pos + sp - 1 >= 500 * (n_regionkey + 1) GROUP BY 1"


@query(_RANGE)
def jn_range_bins(spark, sf):
    """Interval overlap by bins: an equal join on (reference, bin), each pair counted in its first common bin."""
    b = 1000
    spans = alignments(spark, sf).where("ref_id >= 0").select("seq", "ref_id", "pos", (F.col("pos") + F.aggregate(F.regexp_extract_all("cigar", F.lit("([0-9]+)[MDN=X]"), F.lit(1)), F.lit(0).cast("long"), lambda a, x: a + x.cast("long")) - 1).alias("end"))
    panel = table(spark, sf, "nation").selectExpr("n_nationkey panel", "500 * (n_regionkey + 1) p_start", "500 * (n_regionkey + 1) + 3000 p_end")
    left = spans.withColumn("bin", F.explode(F.sequence(F.floor(F.col("pos") / b), F.floor(F.col("end") / b))))
    right = panel.withColumn("bin", F.explode(F.sequence(F.floor(F.col("p_start") / b), F.floor(F.col("p_end") / b))))
    met = left.join(right, (F.col("ref_id") == F.col("panel")) & (left["bin"] == right["bin"]) & (F.col("pos") <= F.col("p_end")) & (F.col("end") >= F.col("p_start")))
    first = F.greatest(F.floor(F.col("pos") / b), F.floor(F.col("p_start") / b))
    return met.where(left["bin"] == first).groupBy("panel").agg(F.count("*").alias("n"))


@query("SELECT a.event_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 1 DAY AND a.ts AND b.event_id <> a.event_id GROUP BY 1")
def jn_interval(spark, sf):
    """Earlier events of the same user within a day, by day bins."""
    e = table(spark, sf, "events").select("event_id", "user_id", "ts", F.to_date("ts").alias("day"))
    left = e.withColumn("bin", F.explode(F.array("day", F.date_sub("day", 1))))
    right = e.select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"), F.col("day").alias("b_day"))
    met = left.join(right, (left["user_id"] == right["b_user"]) & (left["bin"] == right["b_day"]) & (F.col("b_ts") <= F.col("ts")) & (F.col("b_ts") >= F.col("ts") - F.expr("INTERVAL 1 DAY")) & (F.col("b_id") != F.col("event_id")))
    return met.groupBy("event_id").agg(F.count("*").alias("n"))


_ASOF = "SELECT p.event_id, max(c.event_id) AS click_id FROM events p LEFT JOIN events c ON c.user_id = p.user_id AND c.event_type = 'click' AND c.event_id < p.event_id WHERE p.event_type = 'purchase' GROUP BY 1"


@query(_ASOF)
def jn_asof_window(spark, sf):
    """The last click before each purchase: one window over both, no join."""
    e = table(spark, sf, "events").where(F.col("event_type").isin("click", "purchase")).select("event_id", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click_id", last).where("event_type = 'purchase'").select("event_id", "click_id")


@query(_ASOF)
def jn_asof_lateral(spark, sf):
    """The same by a correlated subquery, which looks up its own event in the clicks before each event of a user.

    The lookup is by equal columns alone, so it is an equal join: rows grow with
    the events and not with the purchases times the clicks of a user.
    """
    e = table(spark, sf, "events")
    before = Window.partitionBy("user_id").orderBy("event_id").rangeBetween(Window.unboundedPreceding, -1)
    click = F.max(F.when(F.col("event_type") == "click", F.col("event_id"))).over(before)
    last = e.where(F.col("event_type").isin("click", "purchase")).select("user_id", "event_id", "event_type", click.alias("click_id")).where("event_type = 'purchase'")
    e.createOrReplaceTempView("asof_events")
    last.createOrReplaceTempView("asof_clicks")
    return spark.sql("SELECT p.event_id, max(c.click_id) AS click_id FROM asof_events p LEFT JOIN LATERAL (SELECT max(click_id) AS click_id FROM asof_clicks c WHERE c.user_id = p.user_id AND c.event_id = p.event_id) c WHERE p.event_type = 'purchase' GROUP BY p.event_id")


@query("SELECT a.event_type, count(*) AS n FROM events a JOIN (SELECT event_type, count(*) AS c FROM events GROUP BY 1) b ON a.event_type = b.event_type WHERE c > 10 GROUP BY 1")
def jn_salted(spark, sf):
    """A join on five hot keys: the big side is salted, the small one repeated for each salt."""
    salts = 8
    e = table(spark, sf, "events").select("event_id", "event_type").withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(salts)))
    c = e.groupBy("event_type").agg(F.count("*").alias("c")).where("c > 10").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return e.join(c, ["event_type", "salt"]).groupBy("event_type").agg(F.count("*").alias("n"))


@query("SELECT a.conv_id, a.turn, b.turn AS next_turn, a.role AS role, b.role AS next_role FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1")
def jn_turn_pairs(spark, sf):
    c = table(spark, sf, "conversations").select("conv_id", "turn", "role")
    n = c.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("turn").alias("next_turn"), F.col("role").alias("next_role"))
    return c.join(n, ["conv_id", "turn"]).select("conv_id", "turn", "next_turn", "role", "next_role")


# ---- aggregates -------------------------------------------------------------------------


@query(f"SELECT l_returnflag, l_linestatus, count(*) AS n, sum(cents)::BIGINT AS cents, min(l_partkey) AS low, max(l_partkey) AS high FROM {LI} GROUP BY 1, 2")
def ag_hash(spark, sf):
    return line(spark, sf).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"), F.min("l_partkey").alias("low"), F.max("l_partkey").alias("high"))


@query("SELECT l_returnflag, max(l_linestatus) AS top, array_to_string(list_sort(list_distinct(list(l_linenumber))), ',') AS numbers FROM lineitem GROUP BY 1")
def ag_collect(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.max("l_linestatus").alias("top"), F.array_join(F.sort_array(F.collect_set("l_linenumber")), ",").alias("numbers"))


@query("SELECT event_type, count(DISTINCT user_id) AS users, sum(DISTINCT user_id)::BIGINT AS user_sum FROM events GROUP BY 1")
def ag_distinct(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.sum_distinct("user_id").alias("user_sum"))


@query("SELECT 'within' AS verdict")
def ag_approx(spark, sf):
    """Approximate distinct users, checked against the exact number within five standard errors."""
    e = table(spark, sf, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.count_distinct("user_id").alias("n"))
    return e.select(F.when(F.abs(F.col("a") - F.col("n")) <= 0.1 * F.col("n"), "within").otherwise("outside").alias("verdict"))


@query("SELECT l_linestatus, count(*) FILTER (WHERE l_quantity > 25) AS many, sum(l_linenumber) FILTER (WHERE l_returnflag = 'A')::BIGINT AS a_sum, bool_or(l_tax = 0) AS untaxed, bit_or(l_linenumber) AS bits FROM lineitem GROUP BY 1")
def ag_filter(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_linestatus").agg(F.count_if(F.col("l_quantity") > 25).alias("many"), F.expr("sum(l_linenumber) FILTER (WHERE l_returnflag = 'A')").alias("a_sum"), F.bool_or(F.col("l_tax") == 0).alias("untaxed"), F.bit_or("l_linenumber").alias("bits"))


@query("SELECT lang, max_by(doc_id, n_chars * 1000000 - doc_id) AS longest, min_by(doc_id, n_chars * 1000000 + doc_id) AS shortest FROM documents GROUP BY 1")
def ag_maxby(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.max_by("doc_id", F.col("n_chars") * 1000000 - F.col("doc_id")).alias("longest"), F.min_by("doc_id", F.col("n_chars") * 1000000 + F.col("doc_id")).alias("shortest"))


@query("SELECT l_returnflag, quantile_cont(l_quantity, 0.5)::DOUBLE AS median, quantile_cont(l_quantity, 0.9)::DOUBLE AS p90 FROM lineitem GROUP BY 1")
def ag_percentile(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("median"), F.percentile("l_quantity", 0.9).alias("p90"))


_SETS = "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(cents)::BIGINT AS cents, grouping(l_returnflag, l_linestatus)::BIGINT AS gid FROM {src} GROUP BY {g}"


@query(_SETS.format(src=LI, g="GROUPING SETS ((l_returnflag), (l_linestatus), ())"))
def ag_gsets(spark, sf):
    line(spark, sf).createOrReplaceTempView("gsets_line")
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) n, sum(cents) cents, grouping_id() gid FROM gsets_line GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())").select("l_returnflag", "l_linestatus", "n", "cents", F.col("gid").cast("long").alias("gid"))


@query(_SETS.format(src=LI, g="ROLLUP (l_returnflag, l_linestatus)"))
def ag_rollup(spark, sf):
    return line(spark, sf).rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"), F.grouping_id().cast("long").alias("gid"))


@query(_SETS.format(src=LI, g="CUBE (l_returnflag, l_linestatus)"))
def ag_cube(spark, sf):
    return line(spark, sf).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"), F.grouping_id().cast("long").alias("gid"))


@query("SELECT l_linenumber, count(*) FILTER (WHERE l_returnflag = 'A') AS A, count(*) FILTER (WHERE l_returnflag = 'N') AS N, count(*) FILTER (WHERE l_returnflag = 'R') AS R FROM lineitem GROUP BY 1")
def ag_pivot(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_linenumber").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1))).fillna(0)


@query("SELECT n_nationkey, 'region' AS what, n_regionkey AS value FROM nation UNION ALL SELECT n_nationkey, 'twice', 2 * n_nationkey FROM nation")
def ag_unpivot(spark, sf):
    n = table(spark, sf, "nation").select("n_nationkey", F.col("n_regionkey").alias("region"), (2 * F.col("n_nationkey")).alias("twice"))
    return n.unpivot("n_nationkey", ["region", "twice"], "what", "value")


# ---- windows, order, sets ---------------------------------------------------------------------

_W = "PARTITION BY l_suppkey ORDER BY cents, l_orderkey, l_linenumber, l_partkey"


def _w():
    return Window.partitionBy("l_suppkey").orderBy("cents", "l_orderkey", "l_linenumber", "l_partkey")


@query(f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, row_number() OVER w AS rn, rank() OVER q AS rk, dense_rank() OVER q AS dr, percent_rank() OVER q AS pr, cume_dist() OVER q AS cd FROM {LI} WINDOW w AS ({_W}), q AS (PARTITION BY l_suppkey ORDER BY l_quantity)")
def wn_rank(spark, sf):
    q = Window.partitionBy("l_suppkey").orderBy("l_quantity")
    return line(spark, sf).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.row_number().over(_w()).cast("long").alias("rn"), F.rank().over(q).cast("long").alias("rk"), F.dense_rank().over(q).cast("long").alias("dr"), F.percent_rank().over(q).alias("pr"), F.cume_dist().over(q).alias("cd"))


@query(f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, ntile(4) OVER ({_W}) AS quarter FROM {LI}")
def wn_ntile(spark, sf):
    return line(spark, sf).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.ntile(4).over(_w()).cast("long").alias("quarter"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2, -1) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def wn_lag(spark, sf):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return table(spark, sf, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2, -1).over(w).alias("after"))


@query("SELECT event_id, first_value(event_type) OVER w AS first, last_value(event_type) OVER w AS last, nth_value(event_type, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def wn_first(spark, sf):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf, "events").select("event_id", F.first("event_type").over(w).alias("first"), F.last("event_type").over(w).alias("last"), F.nth_value("event_type", 2).over(w).alias("second"))


_CENTS = "(SELECT *, round(value * 100)::BIGINT AS cents FROM events)"


def _ev(spark, sf):
    return table(spark, sf, "events").withColumn("cents", F.expr("cast(round(value * 100) as bigint)"))


@query(f"SELECT event_id, sum(cents) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS last3 FROM {_CENTS}")
def wn_rows(spark, sf):
    return _ev(spark, sf).select("event_id", F.sum("cents").over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(-2, 0)).alias("last3"))


@query(f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY cents RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM {_CENTS}")
def wn_range(spark, sf):
    return _ev(spark, sf).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("cents").rangeBetween(-100, 100)).alias("near"))


@query(f"SELECT event_id, sum(cents) OVER (PARTITION BY user_id ORDER BY event_id)::BIGINT AS running FROM {_CENTS}")
def wn_running(spark, sf):
    return _ev(spark, sf).select("event_id", F.sum("cents").over(Window.partitionBy("user_id").orderBy("event_id")).alias("running"))


@query("SELECT o_orderkey, row_number() OVER (ORDER BY o_custkey, o_orderkey) AS rank FROM orders")
def so_global(spark, sf):
    from dupflow.queries.methods import _placed

    return _placed(table(spark, sf, "orders").select("o_orderkey", "o_custkey").orderBy("o_custkey", "o_orderkey")).select("o_orderkey", "rank")


@query(f"SELECT l_orderkey, l_linenumber, l_partkey, cents FROM {LI} ORDER BY cents DESC, l_orderkey, l_linenumber, l_partkey LIMIT 25")
def so_topk(spark, sf):
    return line(spark, sf).orderBy(F.desc("cents"), "l_orderkey", "l_linenumber", "l_partkey").limit(25).select("l_orderkey", "l_linenumber", "l_partkey", "cents")


@query(f"SELECT l_suppkey, l_orderkey, l_linenumber, cents FROM (SELECT *, row_number() OVER ({_W}) AS rn FROM {LI}) WHERE rn <= 3")
def so_topk_group(spark, sf):
    return line(spark, sf).withColumn("rn", F.row_number().over(_w())).where("rn <= 3").select("l_suppkey", "l_orderkey", "l_linenumber", "cents")


@query("SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 20")
def so_offset(spark, sf):
    return table(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(20).limit(10).select("o_orderkey")


def _keys(spark, sf):
    a = table(spark, sf, "lineitem").where("l_returnflag = 'A'").select(F.col("l_partkey").alias("k"))
    return a, table(spark, sf, "lineitem").where("l_returnflag = 'R'").select(F.col("l_partkey").alias("k"))


_KA, _KB = "SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'A'", "SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'R'"


@query(f"SELECT k, count(*) AS n FROM ({_KA} UNION ALL {_KB}) GROUP BY k")
def set_union(spark, sf):
    a, b = _keys(spark, sf)
    return a.unionByName(b).groupBy("k").agg(F.count("*").alias("n"))


@query(f"{_KA} INTERSECT {_KB}")
def set_intersect(spark, sf):
    a, b = _keys(spark, sf)
    return a.intersect(b)


@query(f"{_KA} EXCEPT ALL {_KB}")
def set_except_all(spark, sf):
    a, b = _keys(spark, sf)
    return a.exceptAll(b)


@query("SELECT DISTINCT l_suppkey, l_returnflag FROM lineitem")
def set_distinct(spark, sf):
    return table(spark, sf, "lineitem").select("l_suppkey", "l_returnflag").distinct()


# ---- functions ------------------------------------------------------------------------------------


@query("SELECT p_partkey, string_split(p_name, ' ')[1] AS first, substr(p_type, 2, 3) AS mid, lpad(p_size::VARCHAR, 4, '0') AS padded, translate(p_brand, '#0', '-x') AS swapped, length(p_name)::INT AS n, levenshtein(p_brand, p_type)::INT AS far, concat_ws('/', p_brand, p_type) AS both FROM part")
def fn_string(spark, sf):
    p = table(spark, sf, "part")
    return p.select("p_partkey", F.split("p_name", " ")[0].alias("first"), F.substring("p_type", 2, 3).alias("mid"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"), F.translate("p_brand", "#0", "-x").alias("swapped"), F.length("p_name").alias("n"), F.levenshtein("p_brand", "p_type").alias("far"), F.concat_ws("/", "p_brand", "p_type").alias("both"))


@query("SELECT p_partkey, regexp_extract(p_brand, '([0-9]+)', 1) AS number, regexp_replace(p_type, '[AEIOU]', '_', 'g') AS novowel, len(regexp_extract_all(p_name, '[a-z]+'))::INT AS words FROM part")
def fn_regex(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.regexp_extract("p_brand", "([0-9]+)", 1).alias("number"), F.regexp_replace("p_type", "[AEIOU]", "_").alias("novowel"), F.size(F.regexp_extract_all("p_name", F.lit("[a-z]+"), F.lit(0))).alias("words"))


@query("SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, date_diff('day', DATE '1990-01-01', o_orderdate::DATE)::INT AS days, strftime(o_orderdate + INTERVAL 3 DAY, '%Y-%m-%d') AS later FROM orders")
def fn_date(spark, sf):
    o = table(spark, sf, "orders")
    return o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_format(F.date_trunc("month", F.col("o_orderdate").cast("timestamp")), "yyyy-MM-dd").alias("month"), F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01").cast("date")).alias("days"), F.date_format((F.col("o_orderdate") + F.expr("INTERVAL 3 DAY")).cast("timestamp"), "yyyy-MM-dd").alias("later"))


@query("SELECT l_orderkey, l_linenumber, l_partkey, floor(l_quantity / 7)::BIGINT AS sevens, abs(l_partkey - l_suppkey) AS far, (l_partkey % 11 + 11) % 11 AS m, power(l_linenumber, 2)::DOUBLE AS sq, sign(l_quantity - 25)::DOUBLE AS side FROM lineitem")
def fn_math(spark, sf):
    return table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.floor(F.col("l_quantity") / 7).alias("sevens"), F.abs(F.col("l_partkey") - F.col("l_suppkey")).alias("far"), F.pmod("l_partkey", F.lit(11)).alias("m"), F.pow("l_linenumber", F.lit(2)).alias("sq"), F.signum(F.col("l_quantity") - 25).alias("side"))


@query("SELECT l_orderkey, l_linenumber, l_partkey, l_partkey & 255 AS a, l_partkey | 1024 AS o, xor(l_partkey, l_suppkey) AS x, l_partkey << 2 AS l, l_partkey >> 1 AS r, bit_count(l_partkey)::INT AS bits FROM lineitem")
def fn_bits(spark, sf):
    p = F.col("l_partkey")
    return table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", p.bitwiseAND(F.lit(255)).alias("a"), p.bitwiseOR(F.lit(1024)).alias("o"), p.bitwiseXOR(F.col("l_suppkey")).alias("x"), F.shiftleft(p, 2).alias("l"), F.shiftright(p, 1).alias("r"), F.bit_count(p).alias("bits"))


_Q = "list_transform(embedding, lambda x: floor(x::DOUBLE * 100)::BIGINT)"


@query(f"SELECT vec_id, list_sum({_Q})::BIGINT AS total, len(list_filter({_Q}, lambda x: x > 10))::INT AS big, list_max({_Q})::BIGINT AS top, array_to_string(list_sort({_Q})[1:3], ',') AS least, list_contains({_Q}, 0) AS zero FROM embeddings")
def fn_array(spark, sf):
    e = table(spark, sf, "embeddings").select("vec_id", F.transform("embedding", lambda x: F.floor(x.cast("double") * 100)).alias("q"))
    return e.select("vec_id", F.aggregate("q", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.size(F.filter("q", lambda x: x > 10)).alias("big"), F.array_max("q").alias("top"), F.array_join(F.slice(F.array_sort("q"), 1, 3), ",").alias("least"), F.exists("q", lambda x: x == 0).alias("zero"))


@query(AL + "SELECT seq::VARCHAR AS seq, i::INT AS ord, right(x, 1) AS op, left(x, length(x) - 1)::INT AS len FROM (SELECT seq, unnest(ops) AS x, unnest(range(len(ops))) AS i FROM (SELECT seq, regexp_extract_all(cigar, '[0-9]+[MIDNSHP=X]') AS ops FROM al))")
def cigar_explode(spark, sf):
    a = alignments(spark, sf).select(F.col("seq").cast("string").alias("seq"), F.posexplode(cigar_ops(F.col("cigar"))).alias("ord", "o"))
    return a.select("seq", "ord", "o.op", "o.len")


@query("SELECT event_id, (props->>'k')::BIGINT AS k, (props->>'k')::BIGINT * 2 AS twice FROM events")
def fn_map(spark, sf):
    m = table(spark, sf, "events").select("event_id", F.from_json("props", "map<string,bigint>").alias("m"))
    m = m.withColumn("t", F.transform_values(F.map_filter("m", lambda k, v: k == "k"), lambda k, v: v * 2))
    return m.select("event_id", F.col("m")["k"].alias("k"), F.col("t")["k"].alias("twice"))


@query("SELECT event_id, props->>'k' AS k FROM events")
def fn_json(spark, sf):
    return table(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@query("SELECT doc_id, md5(text) AS md5, sha256(text) AS sha256, base64(encode(lang)) AS b64 FROM documents")
def fn_hash(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.md5("text").alias("md5"), F.sha2(F.col("text").cast("binary"), 256).alias("sha256"), F.base64(F.encode("lang", "utf-8")).alias("b64"))


# ---- subqueries, CTEs, user-defined functions, SQL ---------------------------------------------------


@query("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT max(o_totalprice) * 0.9 FROM orders)")
def sq_scalar(spark, sf):
    table(spark, sf, "orders").createOrReplaceTempView("sq_orders")
    return spark.sql("SELECT o_orderkey FROM sq_orders WHERE o_totalprice > (SELECT max(o_totalprice) * 0.9 FROM sq_orders)")


@query("SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_nationkey < 5)")
def sq_exists(spark, sf):
    for t in ("orders", "lineitem", "customer"):
        table(spark, sf, t).createOrReplaceTempView(f"sx_{t}")
    return spark.sql("SELECT o_orderkey FROM sx_orders o WHERE EXISTS (SELECT 1 FROM sx_lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45) AND o_custkey IN (SELECT c_custkey FROM sx_customer WHERE c_nationkey < 5)")


_CTE = "WITH RECURSIVE walk(n, here) AS (SELECT 0, 0 UNION ALL SELECT n + 1, (here * 7 + 3) % 25 FROM walk WHERE n < 30) SELECT n, n_name FROM walk JOIN {nation} ON here = n_nationkey"


@query(_CTE.format(nation="nation"))
def cte_basic(spark, sf):
    table(spark, sf, "nation").createOrReplaceTempView("cte_nation")
    return spark.sql(_CTE.format(nation="cte_nation"))


@query(AL + "SELECT seq::VARCHAR AS seq, score FROM al")
def udf_score(spark, sf):
    """The quality score as a vectorised function of users' own; must equal the built-in form."""
    @F.pandas_udf("long")
    def score(q: pd.Series) -> pd.Series:
        return q.map(lambda s: sum(x - 33 for x in s.encode("latin-1") if x - 33 >= 15))

    return alignments(spark, sf).select(F.col("seq").cast("string").alias("seq"), score("quals").alias("score"))


@query("SELECT user_id, max(round(value * 100)::BIGINT) AS best FROM events GROUP BY 1")
def udaf_best(spark, sf):
    """A user-defined grouped aggregate: partial bests by built-ins, the last step in pandas."""
    @F.pandas_udf("long")
    def best(v: pd.Series) -> int:
        return int(v.max())

    part = _ev(spark, sf).groupBy("user_id", F.pmod("event_id", F.lit(16)).alias("share")).agg(F.max("cents").alias("cents"))
    return part.groupBy("user_id").agg(best("cents").alias("best"))


@query(AL + "SELECT op, sum(len)::BIGINT AS bases FROM (SELECT right(x, 1) AS op, left(x, length(x) - 1)::INT AS len FROM (SELECT unnest(regexp_extract_all(cigar, '[0-9]+[MIDNSHP=X]')) AS x FROM al)) GROUP BY 1")
def udtf_cigar(spark, sf):
    """Mapping operations as rows from a table function."""

    class Ops:
        def eval(self, cigar: str):
            n = ""
            for c in cigar:
                if c.isdigit():
                    n += c
                elif n:
                    yield c, int(n)
                    n = ""

    spark.udtf.register("cigar_rows", F.udtf(Ops, returnType="op: string, len: int"))
    alignments(spark, sf).select("cigar").createOrReplaceTempView("udtf_al")
    return spark.sql("SELECT t.op, sum(t.len) bases FROM udtf_al, LATERAL cigar_rows(cigar) t GROUP BY t.op")


@query(AL + "SELECT ref_id, count(*) AS n FROM al WHERE ref_id >= 0 AND pos <= 5000 AND pos + sp - 1 >= 2000 GROUP BY 1")
def sql_overlap(spark, sf):
    """The overlap predicate as a SQL function over a view; it is inlined."""
    from dupflow.functions.geometry import span

    a = alignments(spark, sf)
    a.select("ref_id", "pos", span(F.col("cigar")).alias("sp")).createOrReplaceTempView("alignment_spans")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION overlaps_span(p BIGINT, s BIGINT, lo BIGINT, hi BIGINT) RETURNS BOOLEAN RETURN p <= hi AND p + s - 1 >= lo")
    return spark.sql("SELECT ref_id, count(*) n FROM alignment_spans WHERE ref_id >= 0 AND overlaps_span(pos, sp, 2000, 5000) GROUP BY ref_id")


@query("SELECT user_id, event_type, floor(value)::BIGINT // 5 AS k, count(*) AS set_size, max_by(event_id, round(value * 100)::BIGINT * 1000000000 - event_id) AS kept FROM events GROUP BY 1, 2, 3")
def sql_mark(spark, sf):
    """Best-of-set from SQL text over a view."""
    table(spark, sf, "events").createOrReplaceTempView("mark_events_view")
    return spark.sql("SELECT user_id, event_type, floor(value) div 5 k, count(*) set_size, max_by(event_id, cast(round(value * 100) as bigint) * 1000000000 - event_id) kept FROM mark_events_view GROUP BY 1, 2, 3")


@query("SELECT count(*) AS n FROM lineitem")
def op_hints(spark, sf):
    """Partitioning hints change the plan and not the rows."""
    return table(spark, sf, "lineitem").hint("rebalance", "l_orderkey").repartition(7, "l_orderkey").coalesce(3).agg(F.count("*").alias("n"))


@query("SELECT 'within' AS verdict")
def op_sample(spark, sf):
    """A seeded sample of a tenth, checked against the whole within five standard errors."""
    t = table(spark, sf, "lineitem")
    both = t.sample(0.1, seed=7).agg(F.count("*").alias("a")).crossJoin(t.agg(F.count("*").alias("n")))
    return both.select(F.when(F.abs(F.col("a") - 0.1 * F.col("n")) <= 5 * F.sqrt(0.09 * F.col("n")), "within").otherwise("outside").alias("verdict"))


# ---- sources and sinks -----------------------------------------------------------------------------------


@query("SELECT doc_id, line AS value FROM (SELECT doc_id, unnest(string_split(replace(text, chr(13), ' '), chr(10))) AS line FROM documents WHERE text IS NOT NULL) WHERE line <> ''")
def src_text(spark, sf):
    path = shared_path(spark, "text")
    d = table(spark, sf, "documents").where("text is not null").select("doc_id", F.replace("text", F.lit("\r"), F.lit(" ")).alias("text"))
    d.select(F.concat_ws("\x01", F.col("doc_id").cast("string"), F.replace("text", F.lit("\n"), F.lit("\x02"))).alias("value")).write.text(path)
    t = spark.read.text(path).select(F.split("value", "\x01", 2).alias("p"))
    return t.select(F.col("p")[0].cast("long").alias("doc_id"), F.explode(F.split(F.col("p")[1], "\x02", -1)).alias("value")).where("value <> ''")


@query("SELECT c_custkey, c_name, c_nationkey, c_mktsegment FROM customer")
def src_csv(spark, sf):
    path = shared_path(spark, "csv")
    table(spark, sf, "customer").select("c_custkey", "c_name", "c_nationkey", "c_mktsegment").write.option("header", True).csv(path)
    return spark.read.schema("c_custkey long, c_name string, c_nationkey int, c_mktsegment string").option("header", True).csv(path)


@query("SELECT event_id, user_id, event_type, props FROM events")
def src_json(spark, sf):
    path = shared_path(spark, "json")
    table(spark, sf, "events").select("event_id", "user_id", "event_type", "props").write.json(path)
    return spark.read.schema("event_id long, user_id long, event_type string, props string").json(path)


@query(AL + "SELECT qname, flag, pos, cigar FROM al")
def snk_parquet_rt(spark, sf):
    """The same rows through three codecs, then read as one and made distinct."""
    a, out = alignments(spark, sf).select("seq", "qname", "flag", "pos", "cigar"), None
    for codec in ("zstd", "snappy", "gzip"):
        path = shared_path(spark, f"pq-{codec}")
        a.write.option("compression", codec).parquet(path)
        r = spark.read.parquet(path)
        out = r if out is None else out.unionAll(r)
    return out.distinct().select("qname", "flag", "pos", "cigar")


@query(AL + "SELECT qname, flag, pos, cigar FROM al")
def snk_taf_rt(spark, sf):
    from dupflow.sources.taf import parse_taf, render_taf

    path = shared_path(spark, "tsv")
    render_taf(alignments(spark, sf)).select("value").write.text(path)
    return parse_taf(spark.read.text(path)).select("qname", "flag", "pos", "cigar")


@query("SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_returnflag <> 'N' GROUP BY 1")
def snk_partitioned_rt(spark, sf):
    """Folders by flag; the filter prunes whole folders."""
    path = shared_path(spark, "parts")
    table(spark, sf, "lineitem").select("l_orderkey", "l_returnflag").repartition("l_returnflag").write.partitionBy("l_returnflag").parquet(path)
    return spark.read.parquet(path).where("l_returnflag <> 'N'").groupBy("l_returnflag").agg(F.count("*").alias("n"))


@query("SELECT l_orderkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def snk_bucketed_rt(spark, sf):
    """Two tables bucketed by the order: the join between them needs no exchange."""
    import uuid

    tag = uuid.uuid4().hex[:12]
    for t, k in (("lineitem", "l_orderkey"), ("orders", "o_orderkey")):
        table(spark, sf, t).select(k).write.bucketBy(8, k).sortBy(k).option("path", shared_path(spark, f"bucket-{t}")).saveAsTable(f"b_{t}_{tag}")
    left, o = spark.table(f"b_lineitem_{tag}"), spark.table(f"b_orders_{tag}")
    return left.hint("merge").join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("l_orderkey").agg(F.count("*").alias("n"))

