"""The relational operations around the methods, as queries, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import udfs
from ..functions.codes import ncode_array
from ..sources.graphs import dense, trade
from ..sources.tables import table
from ..session import cut
from . import oracle as o

Query = Callable[[SparkSession, str], DataFrame]
_REGISTERED: dict[str, tuple[Query, str | None]] = {}


def query(sql: str | None = None):
    def add(f: Query) -> Query:
        _REGISTERED[f.__name__] = (f, sql)
        return f

    return add


def money(c) -> F.Column:
    return F.round(F.sum(F.round(c * 100).cast("long")) / 100, 2)


# ---- scans and filters ----------------------------------------------------------------------------------------------


@query("SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_returnflag = 'R' AND l_quantity BETWEEN 10 AND 20 AND l_shipdate < TIMESTAMP '1995-01-01'")
def r_scan_filter(spark, d):
    li = table(spark, d, "lineitem")
    return li.where((F.col("l_returnflag") == "R") & F.col("l_quantity").between(10, 20) & (F.col("l_shipdate") < F.lit("1995-01-01").cast("timestamp_ntz"))).select("l_orderkey", "l_partkey", "l_quantity")


@query("SELECT p_partkey, p_type FROM part WHERE p_type IN ('PROMO', 'SMALL') AND p_brand LIKE 'Brand#1%' AND regexp_matches(p_name, '[0-9]$') AND NOT p_size <> 10 AND p_type IS NOT DISTINCT FROM 'PROMO'")
def r_scan_predicates(spark, d):
    p = table(spark, d, "part")
    return p.where(F.col("p_type").isin("PROMO", "SMALL") & F.col("p_brand").like("Brand#1%") & F.col("p_name").rlike("[0-9]$") & ~(F.col("p_size") != 10) & F.col("p_type").eqNullSafe("PROMO")).select("p_partkey", "p_type")


@query("SELECT c_custkey AS id, upper(c_mktsegment) AS segment, c_acctbal > 0 AS positive FROM customer")
def r_project(spark, d):
    return table(spark, d, "customer").select(F.col("c_custkey").alias("id"), F.upper("c_mktsegment").alias("segment"), (F.col("c_acctbal") > 0).alias("positive"))


def _round_trip(kind: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        import uuid

        from ..session import shared_dir

        n = table(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey")
        path = f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"
        n.write.format(kind).save(path)
        return spark.read.schema(n.schema).format(kind).load(path)

    run.__name__ = f"r_source_{kind}"
    return run


for _kind in ("csv", "json", "orc", "parquet"):
    query("SELECT n_nationkey, n_name, n_regionkey FROM nation")(_round_trip(_kind))


@query(o.with_(o.graph("D")) + "SELECT src, dst, elabel FROM e")
def r_source_edge_list(spark, d):
    import uuid

    from ..session import shared_dir
    from ..sources.tables import read_edge_list, write_edge_list

    path = f"{shared_dir(spark)}/edges-{uuid.uuid4().hex}"
    write_edge_list(dense(spark, d).edges, path)
    return read_edge_list(spark, path)


@query(o.with_(o.graph("T")) + "SELECT vid, vlabel FROM v WHERE vlabel = 'P:PROMO'")
def r_sink_graph_by_label(spark, d):
    import uuid

    from ..session import shared_dir
    from ..sources.tables import read_graph, write_graph

    path = f"{shared_dir(spark)}/graph-{uuid.uuid4().hex}"
    write_graph(trade(spark, d), path)
    return read_graph(spark, path).vertices.where("vlabel = 'P:PROMO'")


@query("SELECT r_regionkey AS k, r_name AS name FROM region UNION ALL SELECT 99, 'NONE'")
def r_source_rows(spark, d):
    extra = spark.createDataFrame([(99, "NONE")], "k int, name string")
    return table(spark, d, "region").select(F.col("r_regionkey").alias("k"), F.col("r_name").alias("name")).union(extra)


# ---- joins ----------------------------------------------------------------------------------------------------------

_CO = "SELECT c_custkey, o_orderkey FROM customer {} JOIN (SELECT * FROM orders WHERE o_totalprice > 300000) o ON c_custkey = o_custkey"


def _co(spark, d, how: str, hint: str | None = None) -> DataFrame:
    orders = table(spark, d, "orders").where("o_totalprice > 300000").select("o_orderkey", "o_custkey")
    c = table(spark, d, "customer").select("c_custkey")
    return c.join(orders.hint(hint) if hint else orders, F.col("c_custkey") == F.col("o_custkey"), how)


for _how, _word in (("inner", ""), ("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    def _join(spark, d, how=_how):
        return _co(spark, d, how).select("c_custkey", "o_orderkey")

    _join.__name__ = f"r_join_{_how}"
    query(f"SELECT coalesce(c_custkey, -1) AS c_custkey, coalesce(o_orderkey, -1) AS o_orderkey FROM ({_CO.format(_word)})")(lambda spark, d, f=_join: f(spark, d).na.fill(-1))
    _REGISTERED[_join.__name__] = _REGISTERED.pop("<lambda>")

for _hint in ("merge", "shuffle_hash", "broadcast"):
    def _hinted(spark, d, hint=_hint):
        return _co(spark, d, "inner", hint).select("c_custkey", "o_orderkey")

    _hinted.__name__ = f"r_join_hint_{_hint}"
    query(_CO.format(""))(_hinted)


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
def r_join_semi(spark, d):
    return _co(spark, d, "left_semi")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
def r_join_anti(spark, d):
    return _co(spark, d, "left_anti")


@query("SELECT r_name, n_name FROM region CROSS JOIN nation")
def r_join_cross(spark, d):
    """Both tables have a fixed number of rows."""
    return table(spark, d, "region").select("r_name").crossJoin(table(spark, d, "nation").select("n_name"))


@query("SELECT p.p_partkey AS a, count(*) AS n FROM part p JOIN part q ON q.p_size BETWEEN p.p_size - 1 AND p.p_size AND p.p_brand = q.p_brand AND q.p_retailprice < p.p_retailprice GROUP BY 1")
def r_join_range(spark, d):
    p = table(spark, d, "part").select("p_partkey", "p_brand", "p_size", "p_retailprice")
    q = p.select(*(F.col(c).alias(c.replace("p_", "q_")) for c in p.columns))
    # The range side is dealt to the sizes it covers, so the join has keys: brand and size.
    dealt = p.withColumn("size", F.explode(F.array(F.col("p_size") - 1, F.col("p_size"))))
    both = dealt.join(q, (F.col("p_brand") == F.col("q_brand")) & (F.col("size") == F.col("q_size")) & (F.col("q_retailprice") < F.col("p_retailprice")))
    return both.groupBy(F.col("p_partkey").alias("a")).agg(F.count("*").alias("n"))


@query("SELECT p.event_id AS purchase, v.event_id AS view_ FROM (SELECT * FROM events WHERE event_type='purchase') p ASOF JOIN (SELECT * FROM events WHERE event_type='view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def r_join_asof(spark, d):
    """The latest earlier view of each purchase's user: one window over both, no pairs."""
    e = table(spark, d, "events").where("event_type in ('purchase', 'view')").select("event_id", "user_id", "event_type", "ts")
    w = Window.partitionBy("user_id").orderBy("ts", F.desc("event_type")).rowsBetween(Window.unboundedPreceding, 0)
    seen = e.withColumn("view_", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'purchase' and view_ is not null").select(F.col("event_id").alias("purchase"), "view_")


@query("SELECT a.event_id AS click, count(*) AS n FROM events a JOIN events b ON a.user_id=b.user_id AND a.event_type='click' AND b.event_type='view' AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts GROUP BY 1")
def r_join_interval(spark, d):
    """Views within the hour before a click: both sides dealt by user and hour, a click to two hours."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = 3_600_000_000
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("us").alias("at")).withColumn("h", F.explode(F.array(F.floor(F.col("at") / hour), F.floor(F.col("at") / hour) - 1)))
    b = e.where("event_type = 'view'").select("user_id", "us", F.floor(F.col("us") / hour).alias("h"))
    return a.join(b, ["user_id", "h"]).where(F.col("us").between(F.col("at") - hour, F.col("at"))).groupBy("click").agg(F.count("*").alias("n"))


@query("SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON nullif(a.n_regionkey, 0) IS NOT DISTINCT FROM nullif(b.n_regionkey, 0) AND a.n_nationkey < b.n_nationkey")
def r_join_nullsafe(spark, d):
    n = table(spark, d, "nation").select("n_nationkey", "n_name", F.nullif("n_regionkey", F.lit(0)).alias("r"))
    return n.alias("a").join(n.alias("b"), F.col("a.r").eqNullSafe(F.col("b.r")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"))


@query("SELECT n_name, s_suppkey FROM nation, LATERAL (SELECT s_suppkey FROM supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 2)")
def r_join_lateral(spark, d):
    table(spark, d, "nation").createOrReplaceTempView("v_nation")
    table(spark, d, "supplier").createOrReplaceTempView("v_supplier")
    return spark.sql("SELECT n_name, s_suppkey FROM v_nation, LATERAL (SELECT s_suppkey FROM v_supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 2)")


_TRI = o.with_(o.graph("Y")) + "SELECT a.src AS a, a.dst AS b, count(*) AS n FROM e a JOIN e b ON a.dst=b.src JOIN e c ON c.src=a.src AND c.dst=b.dst GROUP BY 1, 2"


@query(_TRI)
def r_multiway_triangles(spark, d):
    """Left-deep: paths, then the closing edge as a join on both keys."""
    from ..sources.graphs import few_labels

    e = few_labels(spark, d).edges.select("src", "dst")
    paths = e.select(F.col("src").alias("a"), F.col("dst").alias("b")).join(e.select(F.col("src").alias("b"), F.col("dst").alias("c")), "b")
    closed = paths.join(e.select(F.col("src").alias("a"), F.col("dst").alias("c")), ["a", "c"])
    return closed.groupBy("a", "b").agg(F.count("*").alias("n"))


@query(_TRI)
def r_multiway_intersect(spark, d):
    """The same by intersecting neighbour lists; for graphs whose largest degree is small, as this one's."""
    from ..sources.graphs import few_labels

    e = few_labels(spark, d).edges.select("src", "dst")
    lists = e.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("near"))
    both = e.join(lists, "src").join(lists.select(F.col("src").alias("dst"), F.col("near").alias("far")), "dst")
    return both.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.size(F.array_intersect("near", "far")).cast("long").alias("n")).where("n > 0")


# ---- aggregates -----------------------------------------------------------------------------------------------------


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, min(l_shipdate) AS first_ship, max(l_tax) AS tax, round(stddev_samp(l_quantity), 4) AS sd FROM lineitem GROUP BY 1, 2")
def r_agg_basic(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_shipdate").alias("first_ship"), F.max("l_tax").alias("tax"), F.round(F.stddev_samp("l_quantity"), 4).alias("sd"))


@query("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1")
def r_agg_distinct(spark, d):
    return table(spark, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders"))


@query("SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus='F') AS finished, sum(CASE WHEN o_totalprice > 100000 THEN 1 ELSE 0 END)::BIGINT AS large, bool_and(o_totalprice > 0) AS all_positive, bool_or(o_orderstatus='P') AS some_p, max_by(o_orderkey, o_totalprice) AS top_order FROM orders GROUP BY 1")
def r_agg_cond(spark, d):
    return table(spark, d, "orders").groupBy("o_orderpriority").agg(F.count(F.when(F.col("o_orderstatus") == "F", 1)).alias("finished"), F.sum((F.col("o_totalprice") > 100000).cast("long")).alias("large"), F.bool_and(F.col("o_totalprice") > 0).alias("all_positive"), F.bool_or(F.col("o_orderstatus") == "P").alias("some_p"), F.max_by("o_orderkey", "o_totalprice").alias("top_order"))


_GROUPED = "SELECT coalesce(p_brand, '*') AS p_brand, coalesce(p_type, '*') AS p_type, grouping(p_brand)*2+grouping(p_type) AS g, count(*) AS n FROM part GROUP BY {}"


def _grouped(frame) -> DataFrame:
    g = (F.grouping("p_brand") * 2 + F.grouping("p_type")).cast("long")
    return frame.agg(g.alias("g"), F.count("*").alias("n")).select(F.coalesce("p_brand", F.lit("*")).alias("p_brand"), F.coalesce("p_type", F.lit("*")).alias("p_type"), "g", "n")


@query(_GROUPED.format("ROLLUP (p_brand, p_type)"))
def r_agg_rollup(spark, d):
    return _grouped(table(spark, d, "part").rollup("p_brand", "p_type"))


@query(_GROUPED.format("CUBE (p_brand, p_type)"))
def r_agg_cube(spark, d):
    return _grouped(table(spark, d, "part").cube("p_brand", "p_type"))


@query(_GROUPED.format("GROUPING SETS ((p_brand), (p_type))"))
def r_agg_gsets(spark, d):
    return _grouped(table(spark, d, "part").groupingSets([["p_brand"], ["p_type"]], "p_brand", "p_type"))


@query("SELECT l_linestatus, count(*) FILTER (WHERE l_returnflag='A') AS \"A\", count(*) FILTER (WHERE l_returnflag='N') AS \"N\", count(*) FILTER (WHERE l_returnflag='R') AS \"R\" FROM lineitem GROUP BY 1")
def r_agg_pivot(spark, d):
    return table(spark, d, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS med, quantile_cont(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY 1")
def r_agg_percentile(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("med"), F.percentile("l_quantity", 0.9).alias("p90"))


@query()
def r_agg_approx(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("med"))


@query("SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS kinds FROM events GROUP BY 1")
def r_agg_sets(spark, d):
    return table(spark, d, "events").groupBy("user_id").agg(F.array_join(F.sort_array(F.collect_set("event_type")), ",").alias("kinds"))


# ---- windows, order, sets -------------------------------------------------------------------------------------------


@query("SELECT p_partkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 6) AS pr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey), v AS (PARTITION BY p_brand ORDER BY p_size)")
def r_win_rank(spark, d):
    w, v = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    return table(spark, d, "part").select("p_partkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("rk"), F.dense_rank().over(v).cast("long").alias("dr"), F.round(F.percent_rank().over(v), 6).alias("pr"))


@query("SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS prev, coalesce(lead(event_id) OVER w, -1) AS next, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def r_win_lag(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events").select("event_id", F.coalesce(F.lag("event_id").over(w), F.lit(-1)).alias("prev"), F.coalesce(F.lead("event_id").over(w), F.lit(-1)).alias("next"), F.first("event_id").over(w).alias("first"))


@query("SELECT o_orderkey, count(*) OVER w AS n, sum(o_orderkey) OVER w::BIGINT AS s FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)".replace("sum(o_orderkey) OVER w::BIGINT", "(sum(o_orderkey) OVER w)::BIGINT"))
def r_win_running(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return table(spark, d, "orders").select("o_orderkey", F.count("*").over(w).alias("n"), F.sum("o_orderkey").over(w).alias("s"))


@query("WITH e AS (SELECT event_id, user_id, epoch_us(ts)//1000000 AS s FROM events) SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM e")
def r_win_range(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", F.unix_seconds(F.col("ts").cast("timestamp")).alias("s"))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("n"))


@query("SELECT s_suppkey, ntile(4) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey) AS q FROM supplier")
def r_win_ntile(spark, d):
    return table(spark, d, "supplier").select("s_suppkey", F.ntile(4).over(Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")).cast("long").alias("q"))


@query(o.with_(o.graph("T")) + ", deg AS (SELECT src AS vid, count(*) AS deg FROM adj GROUP BY 1) SELECT vid, deg FROM deg ORDER BY deg DESC, vid LIMIT 20")
def r_topk_global(spark, d):
    deg = trade(spark, d).adjacency().groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"))
    return deg.orderBy(F.desc("deg"), "vid").limit(20)


@query("SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn FROM part) WHERE rn <= 3")
def r_topk_per_label(spark, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(spark, d, "part").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("p_brand", "p_partkey")


@query("SELECT c_custkey FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10 OFFSET 5")
def r_sort_offset(spark, d):
    return table(spark, d, "customer").orderBy(F.desc("c_acctbal"), "c_custkey").offset(5).limit(10).select("c_custkey")


@query("SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def r_set_union(spark, d):
    c, s = (table(spark, d, t).select(F.col(x).alias("k")) for t, x in (("customer", "c_nationkey"), ("supplier", "s_nationkey")))
    return c.unionByName(s).distinct()


@query("SELECT l_partkey AS k FROM lineitem WHERE l_returnflag='R' INTERSECT SELECT l_partkey FROM lineitem WHERE l_returnflag='A'")
def r_set_intersect(spark, d):
    li = table(spark, d, "lineitem")
    return li.where("l_returnflag = 'R'").select(F.col("l_partkey").alias("k")).intersect(li.where("l_returnflag = 'A'").select(F.col("l_partkey").alias("k")))


@query("SELECT p_partkey AS k FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 45")
def r_set_except(spark, d):
    return table(spark, d, "part").select(F.col("p_partkey").alias("k")).exceptAll(table(spark, d, "lineitem").where("l_quantity > 45").select(F.col("l_partkey").alias("k")).distinct())


@query("SELECT l_suppkey AS k FROM lineitem WHERE l_returnflag='R' INTERSECT ALL SELECT l_suppkey FROM lineitem WHERE l_returnflag='A'")
def r_set_intersect_all(spark, d):
    li = table(spark, d, "lineitem")
    return li.where("l_returnflag = 'R'").select(F.col("l_suppkey").alias("k")).intersectAll(li.where("l_returnflag = 'A'").select(F.col("l_suppkey").alias("k")))


@query("SELECT user_id, event_type, min(event_id) AS event_id FROM events GROUP BY 1, 2")
def r_set_drop_duplicates(spark, d):
    e = table(spark, d, "events").select("user_id", "event_type", "event_id")
    return cut(e, "events").groupBy("user_id", "event_type").agg(F.min("event_id").alias("event_id"))


# ---- functions ------------------------------------------------------------------------------------------------------


@query("SELECT p_partkey, concat(p_brand, '/', p_type) AS a, concat_ws('-', p_type, p_size::VARCHAR) AS b, substring(p_brand, 7) AS c, string_split(p_brand, '#')[2] AS d, regexp_extract(p_brand, '([0-9]+)', 1) AS e, upper(trim(p_name)) AS f, length(p_name) AS g, translate(p_type, 'AEIOU', 'aeiou') AS h FROM part")
def r_fn_string(spark, d):
    return table(spark, d, "part").select("p_partkey", F.concat("p_brand", F.lit("/"), "p_type").alias("a"), F.concat_ws("-", "p_type", F.col("p_size").cast("string")).alias("b"), F.substring("p_brand", 7, 99).alias("c"), F.split("p_brand", "#")[1].alias("d"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("e"), F.upper(F.trim("p_name")).alias("f"), F.length("p_name").cast("long").alias("g"), F.translate("p_type", "AEIOU", "aeiou").alias("h"))


@query("SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m, date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) AS days, year(o_orderdate) AS y, (o_orderdate + INTERVAL 1 MONTH)::DATE::VARCHAR AS later FROM orders")
def r_fn_date(spark, d):
    at = F.col("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.date_trunc("month", at).cast("timestamp_ntz").alias("m"), F.datediff(at, F.lit("1992-01-01")).cast("long").alias("days"), F.year(at).cast("long").alias("y"), F.add_months(at.cast("date"), 1).cast("string").alias("later"))


@query("SELECT p_partkey, round(pow(p_size, 2), 4) AS a, round(sqrt(p_size), 6) AS b, round(ln(p_size), 6) AS c, round(ln(1+p_size), 6) AS d, floor(p_retailprice)::BIGINT AS e, p_partkey % 7 AS f, p_partkey // 7 AS g, greatest(p_size, 10) AS h, least(p_size, 10) AS i, factorial(p_size % 10)::BIGINT AS j, p_size & 5 AS k FROM part")
def r_fn_math(spark, d):
    s, k = F.col("p_size"), F.col("p_partkey")
    return table(spark, d, "part").select("p_partkey", F.round(F.pow(s, F.lit(2)), 4).alias("a"), F.round(F.sqrt(s), 6).alias("b"), F.round(F.ln(s), 6).alias("c"), F.round(F.log1p(s), 6).alias("d"), F.floor("p_retailprice").alias("e"), (k % 7).alias("f"), F.call_function("div", k, F.lit(7)).alias("g"), F.greatest(s, F.lit(10)).alias("h"), F.least(s, F.lit(10)).alias("i"), F.factorial(s % 10).alias("j"), s.bitwiseAND(F.lit(5)).alias("k"))


@query("SELECT p_partkey, sha256(p_name) AS h, md5(p_brand) AS m FROM part")
def r_fn_hash(spark, d):
    return table(spark, d, "part").select("p_partkey", F.sha2("p_name", 256).alias("h"), F.md5("p_brand").alias("m"))


@query("""WITH a AS (SELECT l_orderkey, list_sort(list(DISTINCT l_partkey)) AS p, list_sort(list(DISTINCT l_suppkey)) AS s FROM lineitem GROUP BY 1)
    SELECT l_orderkey, len(p) AS n, p[1] AS first, list_contains(s, 1) AS one, len(list_intersect(p, s)) AS both_, list_sum(list_transform(p, lambda x: x % 10))::BIGINT AS digits, len(list_filter(p, lambda x: x > 1000)) AS large, array_to_string(p[1:2], '|') AS head FROM a""")
def r_fn_array(spark, d):
    a = table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.sort_array(F.collect_set("l_partkey")).alias("p"), F.sort_array(F.collect_set("l_suppkey")).alias("s"))
    return a.select("l_orderkey", F.size("p").cast("long").alias("n"), F.element_at("p", 1).alias("first"), F.array_contains("s", 1).alias("one"), F.size(F.array_intersect("p", "s")).cast("long").alias("both_"), F.aggregate(F.transform("p", lambda x: x % 10), F.lit(0).cast("long"), lambda x, y: x + y).alias("digits"), F.size(F.filter("p", lambda x: x > 1000)).cast("long").alias("large"), F.array_join(F.slice("p", 1, 2), "|").alias("head"))


@query("SELECT user_id, count(*) FILTER (WHERE event_type='view') AS views, count(DISTINCT event_type) AS kinds FROM events GROUP BY 1")
def r_fn_map(spark, d):
    per = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("view")), F.lit(0)).alias("views"), F.size(F.map_filter("m", lambda k, v: v > 0)).cast("long").alias("kinds"))


@query("SELECT event_id, json_extract_string(props, '$.k') AS k, (json_extract_string(props, '$.k')::BIGINT) * 2 AS twice FROM events")
def r_fn_json(spark, d):
    e = table(spark, d, "events")
    return e.select("event_id", F.get_json_object("props", "$.k").alias("k"), (F.from_json("props", "k long")["k"] * 2).alias("twice"))


@query("SELECT l_orderkey, unnest(list_sort(list(l_linenumber))) AS line FROM lineitem GROUP BY 1")
def r_fn_explode(spark, d):
    return table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.sort_array(F.collect_list("l_linenumber")).alias("a")).select("l_orderkey", F.explode("a").alias("line"))


@query("WITH e AS (SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings) SELECT a.vec_id AS id, round(list_dot_product(a.v, b.v)/(sqrt(list_dot_product(a.v, a.v))*sqrt(list_dot_product(b.v, b.v))), 6) AS cos FROM e a JOIN e b ON b.vec_id = 0")
def r_fn_vector(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    one = e.where("vec_id = 0").select(F.col("v").alias("w"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    return e.join(F.broadcast(one)).select(F.col("vec_id").alias("id"), F.round(dot("v", "w") / (F.sqrt(dot("v", "v")) * F.sqrt(dot("w", "w"))), 6).alias("cos"))


# ---- user functions, SQL, samples -----------------------------------------------------------------------------------


@query("WITH c AS (SELECT user_id, count(*) FILTER (WHERE event_type='view') AS a, count(*) FILTER (WHERE event_type='click') AS b FROM events GROUP BY 1) SELECT user_id, (a + (a+b)*(a+b+1)//2)::BIGINT AS code, (a + (a+b)*(a+b+1)//2)::BIGINT AS by_sql FROM c")
def r_udf_code(spark, d):
    """The registered SQL function and the column function agree."""
    udfs.register(spark)
    e = table(spark, d, "events").groupBy("user_id").agg(F.count(F.when(F.col("event_type") == "view", 1)).alias("a"), F.count(F.when(F.col("event_type") == "click", 1)).alias("b"))
    return e.select("user_id", ncode_array(F.array("a", "b")).alias("code"), F.expr("ncode(array(a, b))").alias("by_sql"))


@query("""WITH t AS (SELECT DISTINCT c_mktsegment AS m, o_orderpriority AS p FROM orders JOIN customer ON o_custkey = c_custkey)
    SELECT m, p, u, vlabel, pdeg, code FROM t, LATERAL (VALUES ('a', 'C:'||m, 2::BIGINT, 12::BIGINT), ('b', 'O:'||p, 2, 13), ('c', 'O:'||p, 4, 49), ('d', 'P', 1, 3), ('e', 'S', 1, 3)) v(u, vlabel, pdeg, code)""")
def r_udtf_pattern(spark, d):
    """A pattern's text for each segment and priority that occur together, expanded by the table function."""
    udfs.register(spark)
    both = table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).select(F.col("c_mktsegment").alias("m"), F.col("o_orderpriority").alias("p")).distinct()
    both.withColumn("pattern", F.format_string("(a:C:%s)-(b:O:%s), (a)-(c:O:%s), (b)-(c), (c)-(d:P), (c)-(e:S)", "m", "p", "p")).createOrReplaceTempView("v_patterns")
    return spark.sql("SELECT m, p, u, vlabel, CAST(pdeg AS BIGINT) AS pdeg, code FROM v_patterns, LATERAL expand_pattern(pattern)")


@query("""WITH c AS (SELECT user_id, count(*) FILTER (WHERE event_type='view') AS a, count(*) FILTER (WHERE event_type='click') AS b FROM events GROUP BY 1)
    SELECT user_id, r.rank::BIGINT AS rank, CASE r.rank WHEN 1 THEN a ELSE b END AS n FROM c, (VALUES (1), (2)) r(rank)""")
def r_udtf_decode(spark, d):
    """Each user's code of views and clicks, decoded again by the table function."""
    udfs.register(spark)
    e = table(spark, d, "events").groupBy("user_id").agg(F.count(F.when(F.col("event_type") == "view", 1)).alias("a"), F.count(F.when(F.col("event_type") == "click", 1)).alias("b"))
    e.select("user_id", ncode_array(F.array("a", "b")).alias("code")).createOrReplaceTempView("v_codes")
    return spark.sql("SELECT user_id, CAST(rank AS BIGINT) AS rank, n FROM v_codes, LATERAL decode_code(code, 2)")


@query("WITH c AS (SELECT user_id, count(*) FILTER (WHERE event_type='click') AS a, count(*) FILTER (WHERE event_type='view') AS b FROM events GROUP BY 1) SELECT user_id, (a + (a+b)*(a+b+1)//2)::BIGINT AS code FROM c")
def r_udaf_code(spark, d):
    """A grouped pandas aggregate over the counts of two event types."""
    kinds = spark.createDataFrame([("click",), ("view",)], "event_type string")
    users = table(spark, d, "events").select("user_id").distinct().crossJoin(F.broadcast(kinds))
    n = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    full = users.join(n, ["user_id", "event_type"], "left").select("user_id", "event_type", F.coalesce("n", F.lit(0)).alias("n"))
    return full.repartition("user_id").sortWithinPartitions("user_id", "event_type").groupBy("user_id").agg(udfs.ncode_agg("n").alias("code"))


@query("SELECT c_mktsegment, count(*) AS n FROM customer JOIN orders ON c_custkey=o_custkey WHERE o_orderpriority = '1-URGENT' GROUP BY 1 HAVING count(*) > 1")
def r_sql_front(spark, d):
    table(spark, d, "customer").createOrReplaceTempView("v_customer")
    table(spark, d, "orders").createOrReplaceTempView("v_orders")
    return spark.sql("SELECT c_mktsegment, count(*) AS n FROM v_customer JOIN v_orders ON c_custkey = o_custkey WHERE o_orderpriority = '1-URGENT' GROUP BY 1 HAVING count(*) > 1")


@query()
def r_sample(spark, d):
    return table(spark, d, "lineitem").sample(0.1, seed=1).groupBy("l_returnflag").agg(F.count("*").alias("n"))


@query()
def r_sample_by(spark, d):
    return trade(spark, d).vertices.sampleBy("vlabel", {"P:PROMO": 0.5, "S:ASIA": 1.0}, seed=1)


def queries() -> dict[str, Query]:
    return {n: f for n, (f, _) in _REGISTERED.items()}


def oracle_sql() -> dict[str, str]:
    return {n: s for n, (_, s) in _REGISTERED.items() if s}
