"""Queries over the matching methods, with SQL that returns the same rows where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import codes
from ..operators import baselines, filters, fixpoint, gindex, graph, search
from ..operators.pattern import Pattern, parse
from ..sources import graphs
from ..session import cut
from ..streaming import edgepass, live
from . import oracle as o
from . import measures, workloads
from .match import count, match, match_sql, register_views, run_set, same_rows

Query = Callable[[SparkSession, str], DataFrame]

EDGE = parse("(c:C:BUILDING)-[placed]-(o:O:1-URGENT)")
PATH3 = parse("(c:C:BUILDING)-(o:O:1-URGENT)-(p:P:PROMO)")
TRIANGLE = parse("(o:O:1-URGENT)-(p:P:PROMO), (o)-(s:S:ASIA), (p)-(s)")
TAILED = parse("(c:C:BUILDING)-(o:O:1-URGENT), (o)-(p:P:PROMO), (o)-(s:S:ASIA), (p)-(s)")
STAR3 = parse("(o:O:1-URGENT)-(a:P:PROMO), (o)-(b:P:STANDARD), (o)-(d:P:ECONOMY)")
SAME = parse("(a:P:PROMO)-(o:O:1-URGENT)-(b:P:PROMO)")
SQUARE = parse("(a:Brand#1)-(s:N15)-(b:Brand#2)-(t:N15), (t)-(a)")
CLIQUE4 = parse("(a:Brand#15/0)-(b:Brand#20/1), (a)-(c:Brand#12/1), (a)-(d:Brand#10/2), (b)-(c), (b)-(d), (c)-(d)")
RELATIONS = parse("(o:O:1-URGENT)-[contains]-(p:P:PROMO), (o)-[sourced]-(s:S:ASIA), (p)-[supplies]-(s)")
FLAGGED = parse("(a:Brand#1)-[R]-(s:N15)-[A]-(b:Brand#2)")
DIRPATH = parse("(a:view)-[<1d]->(b:click)-[<1d]->(c:purchase)")
DIRANY = parse("(a:view)->(b:click)->(c:purchase)")
SINGLE = parse("(a:P:PROMO)")
APART = parse("(c:C:BUILDING)-(o:O:1-URGENT), (x:S:ASIA)")
ABSENT = parse("(o:O:1-URGENT)-(x:X:NOWHERE)")

FIXED: dict[str, tuple[str, Pattern]] = {
    "edge": ("T", EDGE), "path3": ("T", PATH3), "triangle": ("T", TRIANGLE), "tailed": ("T", TAILED), "star3": ("T", STAR3),
    "same_label": ("T", SAME), "square": ("D", SQUARE), "clique4": ("Y", CLIQUE4), "edge_labelled": ("T", RELATIONS),
    "edge_flagged": ("D", FLAGGED), "directed_path": ("E", DIRPATH), "directed_any": ("E", DIRANY), "single": ("T", SINGLE),
}


def view(spark: SparkSession, sf_dir: str, name: str) -> graph.LabeledGraph:
    return graphs.GRAPHS[name](spark, sf_dir)


def features(spark: SparkSession, d: str, name: str, q: Pattern, mnd: bool = False) -> DataFrame:
    s = filters.start(view(spark, d, name), q)
    f = filters.one_hop(s)
    return filters.with_mnd(f, s) if mnd else f


def _xs(q: Pattern) -> list:
    return [F.col(c) for c in filters.count_columns(len(q.labels))]


_REGISTERED: dict[str, tuple[Query, str | None]] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        _REGISTERED[name or f.__name__] = (f, sql)
        return f

    return add


# ---- graphs ---------------------------------------------------------------------------------------------------------

for _n, _full in (("T", "trade"), ("D", "dense"), ("Y", "fewlabel"), ("H", "manylabel"), ("E", "event")):
    _edges = o.with_(o.graph(_n))
    _kind = "succession" if _n == "E" else "edges"
    query(_edges + "SELECT src, dst, elabel FROM e", f"g_{_full}_{_kind}")(lambda spark, d, n=_n: view(spark, d, n).edges)
    query(_edges + "SELECT vid, vlabel FROM v", f"g_{_full}_vertices")(lambda spark, d, n=_n: view(spark, d, n).vertices)
    query(_edges + "SELECT vlabel, count(*) AS n FROM v GROUP BY 1", f"g_label_histogram_{_full}")(lambda spark, d, n=_n: graph.label_histogram(view(spark, d, n)))
    query(
        _edges + """, deg AS (SELECT src AS vid, count(*) AS deg FROM adj GROUP BY 1)
        SELECT count(*) AS n_vertices, (sum(deg)/2)::BIGINT AS n_edges, count(DISTINCT vlabel) AS n_labels, round(avg(deg), 6) AS avg_degree, max(deg) AS max_degree, round(sum(deg)/(count(*)*(count(*)-1.0)), 9) AS density FROM deg JOIN v USING (vid)""",
        f"g_summary_{_full}",
    )(lambda spark, d, n=_n: graph.summary(view(spark, d, n)))


@query(o.with_(o.graph("T")) + "SELECT v.vid, count(a.dst) AS deg FROM v LEFT JOIN adj a ON a.src=v.vid GROUP BY 1")
def g_degree_table(spark, d):
    return graph.degrees(view(spark, d, "T"))


@query("SELECT conv_id AS graph_id, (1000000000000000+conv_id*100000+turn)::BIGINT AS src, (1000000000000000+conv_id*100000+nxt)::BIGINT AS dst FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL")
def g_conversation_edges(spark, d):
    return graphs.conversation_graphs(spark, d)[1].select("graph_id", "src", "dst")


@query(
    f"""WITH s AS (SELECT DISTINCT l_orderkey AS g, {2 * o.SPACE}+l_orderkey AS a, {3 * o.SPACE}+l_partkey AS b, 'contains' AS k FROM lineitem UNION ALL SELECT DISTINCT l_orderkey, {2 * o.SPACE}+l_orderkey, {4 * o.SPACE}+l_suppkey, 'sourced' FROM lineitem UNION ALL SELECT DISTINCT l_orderkey, {3 * o.SPACE}+l_partkey, {4 * o.SPACE}+l_suppkey, 'supplies' FROM lineitem)
    SELECT g AS graph_id, count(*) AS n_edges, count(*) FILTER (k='supplies') AS n_supplies FROM s GROUP BY 1"""
)
def g_order_graphs(spark, d):
    return graphs.order_graphs(spark, d)[1].groupBy("graph_id").agg(F.count("*").alias("n_edges"), F.count(F.when(F.col("elabel") == "supplies", 1)).alias("n_supplies"))


@query(
    f"""WITH l AS (SELECT DISTINCT doc_id, trim(x) AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE trim(x) <> ''),
    u AS (SELECT line, min(doc_id) AS first FROM l GROUP BY 1)
    SELECT DISTINCT {7 * o.SPACE}+first AS src, {7 * o.SPACE}+doc_id AS dst FROM l JOIN u USING (line) WHERE doc_id <> first"""
)
def g_doc_shared_lines(spark, d):
    return graphs.document_lines(spark, d).edges.select("src", "dst")


@query(
    f"""WITH l AS (SELECT DISTINCT doc_id, trim(x) AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE trim(x) <> '')
    SELECT {7 * o.SPACE}+doc_id AS vid, sha256(line) AS line FROM l WHERE line IN (SELECT line FROM l GROUP BY 1 HAVING count(*) >= 2)"""
)
def g_doc_line_members(spark, d):
    return graphs.document_line_members(spark, d)


@query(
    f"""WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings)
    SELECT {8 * o.SPACE}+a.vec_id AS src, {8 * o.SPACE}+b.vec_id AS dst FROM e a JOIN e b ON a.vec_id<b.vec_id WHERE list_dot_product(a.v, b.v)/(sqrt(list_dot_product(a.v, a.v))*sqrt(list_dot_product(b.v, b.v))) > 0.3"""
)
def g_vector_similarity(spark, d):
    return graphs.vector_neighbours(spark, d).edges.select("src", "dst")


@query("""SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, target, count(*) AS n FROM (SELECT page_id, url, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS target FROM pages) GROUP BY 1, 2, 3""")
def g_page_links(spark, d):
    return graphs.page_links(spark, d)


@query(
    o.with_(o.graph("Y"), *(["a0 AS (SELECT src, dst FROM adj)"] + [f"k{r} AS (SELECT src AS vid FROM a{r} GROUP BY 1 HAVING count(*)>=8), a{r + 1} AS (SELECT a.* FROM a{r} a JOIN k{r} s ON s.vid=a.src JOIN k{r} t ON t.vid=a.dst)" for r in range(14)])) + "SELECT DISTINCT src AS vid FROM a14"
)
def g_k_core(spark, d):
    return graph.k_core(view(spark, d, "Y"), 8)


@query("WITH RECURSIVE " + o.graph("E") + ", r AS (SELECT vid, vid AS c FROM v UNION SELECT a.dst, r.c FROM r JOIN adj a ON a.src=r.vid WHERE r.c < a.dst) SELECT vid, min(c) AS component FROM r GROUP BY 1", "g_components")
def g_components(spark, d):
    return graph.connected_components(view(spark, d, "E"))


@query(
    "WITH RECURSIVE " + o.graph("Y") + f", b AS (SELECT {3 * o.SPACE}+1 AS vid, 0 AS level UNION SELECT a.dst, b.level+1 FROM b JOIN adj a ON a.src=b.vid WHERE b.level<3) SELECT vid, min(level)::INTEGER AS level FROM b GROUP BY 1"
)
def g_bfs_levels(spark, d):
    return graph.bfs_levels(view(spark, d, "Y"), spark.range(1).select(F.lit(3 * o.SPACE + 1).alias("vid")), 3)


# ---- codes ----------------------------------------------------------------------------------------------------------

_F3 = o.features("T", TRIANGLE)
_H = "({0})", "(({0})*(({0})+1)//2)", "(({0})*(({0})+1)*(({0})+2)//6)", "(({0})*(({0})+1)*(({0})+2)*(({0})+3)//24)"
_SUMS = ["x1", "x1+x2", "x1+x2+x3", "x1+x2+x3+x4"]


def _code_sql(sums: list[str], kind: str = "HUGEINT") -> str:
    return " + ".join(h.format(f"({s})::{kind}") for h, s in zip(_H, sums, strict=False))


@query(_F3 + "SELECT vid, vlabel, x1, x2, x3 FROM f")
def c_onehop_counts(spark, d):
    return features(spark, d, "T", TRIANGLE).select("vid", "vlabel", "x1", "x2", "x3")


@query(_F3 + "SELECT vid, pdeg FROM f")
def c_pattern_degree(spark, d):
    return features(spark, d, "T", TRIANGLE).select("vid", "pdeg")


@query(_F3 + f"SELECT vid, CASE WHEN pdeg <= {TRIANGLE.max_degree} THEN ({_code_sql(_SUMS[:3])})::BIGINT ELSE -1 END AS code FROM f")
def c_code_small(spark, d):
    return features(spark, d, "T", TRIANGLE).select("vid", F.coalesce(codes.ncode_column(_xs(TRIANGLE), TRIANGLE.max_degree), F.lit(-1)).alias("code"))


@query(_F3 + f"SELECT vid, ({_code_sql(_SUMS[:3])})::BIGINT AS code FROM f")
def c_code_full(spark, d):
    return features(spark, d, "T", TRIANGLE).select("vid", codes.ncode_column(_xs(TRIANGLE)).alias("code"))


@query(_F3 + f"SELECT vid, (({_code_sql(_SUMS[:3])})::DECIMAL(38,0))::VARCHAR AS code FROM f")
def c_code_decimal(spark, d):
    return features(spark, d, "T", TRIANGLE).select("vid", codes.ncode_decimal(_xs(TRIANGLE)).cast("string").alias("code"))


@query(_F3 + f"SELECT vid, ({_code_sql(_SUMS[:3])})::BIGINT AS code FROM f")
def c_code_array(spark, d):
    return features(spark, d, "T", TRIANGLE).select("vid", codes.ncode_array(F.array(*_xs(TRIANGLE))).alias("code"))


@query(_F3 + f"SELECT vid, lower(lpad(hex(({_code_sql(_SUMS[:3])})::BIGINT), 128, '0')) AS code FROM f")
def c_code_bytes(spark, d):
    x = F.array(*_xs(TRIANGLE))
    return features(spark, d, "T", TRIANGLE).select("vid", F.lower(F.hex(codes.ncode_bytes(x))).alias("code"))


@query(_F3 + f"SELECT vid, round(ln(1 + ({_code_sql(_SUMS[:3], 'DOUBLE')})), 6) AS code FROM f".replace("//", "/"))
def c_code_log(spark, d):
    return features(spark, d, "T", TRIANGLE).select("vid", F.round(codes.ncode_log(_xs(TRIANGLE)), 6).alias("code"))


@query(_F3 + "SELECT vid, x1 AS p1, x2 AS p2, x3 AS p3 FROM f")
def c_packets_w1(spark, d):
    p = codes.packet_columns(_xs(TRIANGLE), 1)
    return features(spark, d, "T", TRIANGLE).select("vid", *(p[k].alias(f"p{k + 1}") for k in range(3)))


@query(_F3 + f"SELECT vid, ({_code_sql(['x1', 'x1+x2'])})::BIGINT AS p1, x3 AS p2 FROM f")
def c_packets_w2(spark, d):
    p = codes.packet_columns(_xs(TRIANGLE), 2)
    return features(spark, d, "T", TRIANGLE).select("vid", p[0].alias("p1"), p[1].alias("p2"))


@query("SELECT o_orderkey, ((o_orderkey+o_custkey)*(o_orderkey+o_custkey+1)//2+o_custkey)::BIGINT AS c, o_orderkey AS a, o_custkey AS b FROM orders")
def c_pairing(spark, d):
    t = graphs.table(spark, d, "orders").select("o_orderkey", codes.pair_column(F.col("o_orderkey"), F.col("o_custkey")).alias("c"))
    a, b = codes.unpair_column(F.col("c"))
    return t.select("o_orderkey", "c", a.alias("a"), b.alias("b"))


@query("WITH p AS (SELECT o_orderkey, o_custkey%50 AS a, o_orderkey%50 AS b, (o_orderkey//7)%50 AS c FROM orders), q AS (SELECT *, (a+b)*(a+b+1)//2+b AS l, (b+c)*(b+c+1)//2+c AS r FROM p) SELECT o_orderkey, ((l+c)*(l+c+1)//2+c)::BIGINT AS left_first, ((a+r)*(a+r+1)//2+r)::BIGINT AS right_first FROM q")
def c_pairing_nested(spark, d):
    t = graphs.table(spark, d, "orders")
    three = [F.col("o_custkey") % 50, F.col("o_orderkey") % 50, F.call_function("div", F.col("o_orderkey"), F.lit(7)) % 50]
    return t.select("o_orderkey", codes.pair_nested_column(three, "left").alias("left_first"), codes.pair_nested_column(three, "right").alias("right_first"))


@query(_F3 + f", c AS (SELECT pdeg, ({_code_sql(_SUMS[:3])}) AS code FROM f) SELECT pdeg, min(code)::BIGINT AS least, max(code)::BIGINT AS most, bool_and(code BETWEEN {_H[2].format('pdeg')} AND {_H[2].format('pdeg+1')}-1) AS inside FROM c WHERE pdeg > 0 GROUP BY 1")
def c_band_check(spark, d):
    f = features(spark, d, "T", TRIANGLE).where("pdeg > 0").select("pdeg", codes.ncode_column(_xs(TRIANGLE)).alias("code"))
    low, high = codes.step_hof(3, F.col("pdeg")), codes.step_hof(3, F.col("pdeg") + 1) - 1
    return f.groupBy("pdeg").agg(F.min("code").alias("least"), F.max("code").alias("most"), F.bool_and(F.col("code").between(low, high)).alias("inside"))


_S5, _S6 = "(x1+x2+x3+e1+e2)::HUGEINT", "(x1+x2+x3+e1+e2+e3)::HUGEINT"
_STEP5 = "*".join(f"({_S5}+{t})" for t in range(5)) + "//120"
_STEP6 = "*".join(f"({_S6}+{t})" for t in range(6)) + "//720"
_REL = ["contains", "sourced", "supplies"]
_FE = o.with_(o.graph("T"), o.pruned(RELATIONS), f"fe AS (SELECT v.vid, v.vlabel, {', '.join(f'count(*) FILTER (WHERE a.dlabel={o.text(n)}) AS x{k}' for k, n in enumerate(RELATIONS.labels, 1))}, {', '.join(f'count(*) FILTER (WHERE a.elabel={o.text(n)}) AS e{k}' for k, n in enumerate(_REL, 1))}, count(a.dst) AS pdeg FROM lv v LEFT JOIN la a ON a.src=v.vid GROUP BY 1, 2)")


@query(_FE + f", c AS (SELECT vid, ({_code_sql(_SUMS[:3])}) AS cv, ({_code_sql(['e1', 'e1+e2', 'e1+e2+e3'])}) AS ce FROM fe) SELECT vid, cv::VARCHAR AS vertex_code, ce::VARCHAR AS edge_code, ({_code_sql(['cv', 'cv+ce'])})::VARCHAR AS code FROM c")
def c_code_edge_aware(spark, d):
    """Codes of all vertices, in digits as hubs' codes have no bound."""
    f = filters.one_hop(filters.start(view(spark, d, "T"), RELATIONS), _REL)
    f = f.select("vid", codes.ncode_text(F.array(*_xs(RELATIONS))).alias("vertex_code"), codes.ncode_text(F.array("e1", "e2", "e3")).alias("edge_code"))
    return f.withColumn("code", codes.ncode_text(F.array("vertex_code", "edge_code")))


_SHARED = [f"x{k}+e{k}" for k in (1, 2, 3)]


@query(_FE + f"SELECT vid, ({_code_sql(['+'.join(_SHARED[:k]) for k in (1, 2, 3)])})::VARCHAR AS shared, ({_code_sql(_SUMS[:3] + ['x1+x2+x3+e1'])} + ({_STEP5}) + ({_STEP6}))::VARCHAR AS separate FROM fe")
def c_code_edge_dims(spark, d):
    """Edge labels in the vertex labels' dimensions (rank by rank added), or in dimensions of their own after them."""
    f = filters.one_hop(filters.start(view(spark, d, "T"), RELATIONS), _REL)
    x, e = _xs(RELATIONS), [F.col(f"e{j}") for j in (1, 2, 3)]
    return f.select("vid", codes.ncode_text(codes.edge_dims(x, e, "shared")).alias("shared"), codes.ncode_text(codes.edge_dims(x, e, "separate")).alias("separate"))


_GAPS = ["<1d", "<1h", ">=1d"]


@query(
    o.with_(o.graph("E", True), o.pruned(DIRANY), f"fe AS (SELECT v.vid, {', '.join(f'count(*) FILTER (WHERE a.dlabel={o.text(n)}) AS x{k}' for k, n in enumerate(DIRANY.labels, 1))}, {', '.join(f'''count(*) FILTER (WHERE a.elabel={o.text(n)} AND a.dir='{w.upper()}') AS {w}{k}''' for k, n in enumerate(_GAPS, 1) for w in 'io')} FROM lv v LEFT JOIN la a ON a.src=v.vid GROUP BY 1)", f"c AS (SELECT vid, {_code_sql(_SUMS[:3])} AS cv, {_code_sql(['i1', 'i1+i2', 'i1+i2+i3'])} AS ci, {_code_sql(['o1', 'o1+o2', 'o1+o2+o3'])} AS co FROM fe)")
    + f"SELECT vid, cv::BIGINT AS vertex_code, ci::BIGINT AS in_code, co::BIGINT AS out_code, ({_code_sql(['cv', 'cv+ci', 'cv+ci+co'])})::BIGINT AS code FROM c"
)
def c_code_directed(spark, d):
    f = filters.one_hop(filters.start(view(spark, d, "E"), DIRANY), _GAPS)
    of = lambda kind: codes.ncode_column([F.col(f"{kind}{j}") for j in (1, 2, 3)])
    f = f.select("vid", of("x").alias("vertex_code"), of("i").alias("in_code"), of("o").alias("out_code"))
    return f.withColumn("code", codes.ncode_column([F.col("vertex_code"), F.col("in_code"), F.col("out_code")]))


_HOPS = o.with_(
    o.graph("Y"), o.pruned(CLIQUE4), "n1 AS (SELECT DISTINCT src AS vid, dst AS w FROM la)",
    "n2 AS (SELECT DISTINCT a.vid, b.w FROM n1 a JOIN n1 b ON b.vid=a.w WHERE a.vid<>b.w EXCEPT SELECT vid, w FROM n1)",
    "far AS (SELECT vid, w, 1 AS at_ FROM n1 UNION ALL SELECT vid, w, 2 FROM n2)",
    f"hc AS (SELECT v.vid, v.vlabel, {', '.join(f'count(*) FILTER (WHERE f.at_={h} AND d.vlabel={o.text(n)}) AS s{h}_{k}' for h in (1, 2) for k, n in enumerate(CLIQUE4.labels, 1))} FROM lv v LEFT JOIN far f ON f.vid=v.vid LEFT JOIN lv d ON d.vid=f.w GROUP BY 1, 2)",
)


def _hops(spark, d):
    return filters.hop_counts(filters.start(view(spark, d, "Y"), CLIQUE4), 2)


@query(_HOPS + f"SELECT vid, {', '.join(f's1_{k}+s2_{k} AS b{k}' for k in range(1, 5))} FROM hc")
def c_ball2_counts(spark, d):
    return _hops(spark, d).select("vid", *((F.col(f"s1_{k}") + F.col(f"s2_{k}")).alias(f"b{k}") for k in range(1, 5)))


@query(_HOPS + f"SELECT vid, {', '.join(f's2_{k} AS b{k}' for k in range(1, 5))} FROM hc")
def c_shell2_counts(spark, d):
    return _hops(spark, d).select("vid", *(F.col(f"s2_{k}").alias(f"b{k}") for k in range(1, 5)))


def _prefix_sql(kind: str) -> list[str]:
    return ["+".join(kind.format(i) for i in range(1, k + 1)) for k in range(1, 5)]


@query(_HOPS + f"SELECT vid, ({_code_sql(_prefix_sql('s1_{0}+s2_{0}'))})::BIGINT AS ball, ({_code_sql(_prefix_sql('s1_{0}'))})::BIGINT AS shell1, ({_code_sql(_prefix_sql('s2_{0}'))})::BIGINT AS shell2 FROM hc")
def c_hop_codes(spark, d):
    of = lambda h, up: codes.ncode_column(filters._hop_columns(CLIQUE4, h, up))
    return _hops(spark, d).select("vid", of(2, True).alias("ball"), of(1, False).alias("shell1"), of(2, False).alias("shell2"))


@query()
def c_decode(spark, d):
    """Codes of all vertices, in digits as hubs' have no bound, decoded again; tests hold it against the vectors."""
    from ..functions.udfs import decode_column

    f = features(spark, d, "T", TRIANGLE).select("vid", "x1", "x2", "x3", codes.ncode_text(F.array(*_xs(TRIANGLE))).alias("code"))
    v = decode_column(3)(F.col("code"))
    return f.select("vid", "code", (v == F.array("x1", "x2", "x3")).alias("same"))


@query()
def c_widths(spark, d):
    """Labels whose codes fit 64 bits and 38 digits, by how many events a user has; tests hold it against plain integers."""
    degrees = graphs.table(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("users"))
    width = lambda limit: F.pandas_udf(lambda n: n.map(lambda x: codes.max_width(int(x), limit)).astype("int32"), "int")
    return degrees.select("degree", "users", width(codes.INT64)("degree").alias("long_width"), width(codes.DECIMAL)("degree").alias("decimal_width"))


# ---- filters --------------------------------------------------------------------------------------------------------

for _kind, _test in (("label", filters.label), ("degree", filters.degree), ("mnd", filters.mnd), ("nlf", filters.nlf), ("mnd_nlf", filters.mnd_nlf), ("lemma", filters.code_lemma), ("strict", filters.code_strict)):
    _name = f"f_code_{_kind}" if _kind in ("lemma", "strict") else f"f_{_kind}"
    _sql = o.with_(o.graph("T"), o.pruned(TAILED), o.counts(TAILED), o.mnd()) + o.candidates(TAILED, _kind, "m")
    query(_sql, _name)(lambda spark, d, t=_test, m="mnd" in _kind: filters.candidates(features(spark, d, "T", TAILED, m), TAILED, t))

query(o.features("T", TAILED) + o.candidates(TAILED, "nlf"), "f_packets_w1")(lambda spark, d: filters.candidates(features(spark, d, "T", TAILED), TAILED, filters.code_packets(1)))
query(o.features("T", TAILED) + o.candidates(TAILED, "strict"), "f_packets_full")(lambda spark, d: filters.candidates(features(spark, d, "T", TAILED), TAILED, filters.code_packets(4)))


def _packet2_sql() -> str:
    out = []
    for u in sorted(TAILED.vertices):
        x = TAILED.vector(u)
        tests = [f"vlabel={o.text(TAILED.vertices[u])}"]
        for k in (0, 2):
            a, b = f"x{k + 1}", f"x{k + 2}"
            tests.append(f"({a}+{b}>{x[k] + x[k + 1]} OR ({a}={x[k]} AND {b}={x[k + 1]}))")
        out.append(f"SELECT {o.text(u)} AS u, vid FROM f WHERE {' AND '.join(tests)}")
    return " UNION ALL ".join(out)


query(o.features("T", TAILED) + o.candidates(TAILED, "strict"), "f_packets_auto")(lambda spark, d: filters.candidates(features(spark, d, "T", TAILED), TAILED, filters.code_packets()))
query(o.features("T", TAILED) + o.candidates(TAILED, "lemma"), "f_code_log")(lambda spark, d: filters.candidates(features(spark, d, "T", TAILED), TAILED, filters.code_log()))


def _full_degree_sql() -> str:
    parts = [f"SELECT {o.text(u)} AS u, vid FROM w WHERE vlabel={o.text(n)} AND deg>={TAILED.pdeg(u)}" for u, n in sorted(TAILED.vertices.items())]
    return o.with_(o.graph("T"), "w AS (SELECT v.vid, v.vlabel, count(a.dst) AS deg FROM v LEFT JOIN adj a ON a.src=v.vid GROUP BY 1, 2)") + " UNION ALL ".join(parts)


@query(_full_degree_sql())
def f_full_degree(spark, d):
    """Degrees of the whole graph, where f_degree counts edges between pattern labels only."""
    g = view(spark, d, "T")
    return filters.candidates(filters.unrestricted_degree(g, filters.start(g, TAILED).vertices), TAILED, filters.full_degree)


query(o.features("T", TAILED) + _packet2_sql(), "f_packets_w2")(lambda spark, d: filters.candidates(features(spark, d, "T", TAILED), TAILED, filters.code_packets(2)))


@query(o.with_(o.graph("T"), o.pruned(TAILED)) + "SELECT s.vlabel AS a, d.vlabel AS b, count(*) AS n FROM la JOIN lv s ON s.vid=la.src JOIN lv d ON d.vid=la.dst GROUP BY 1, 2")
def f_edge_triples(spark, d):
    s = filters.start(view(spark, d, "T"), TAILED)
    names = s.vertices.select("vid", "vlabel")
    both = s.adj.join(names.select(F.col("vid").alias("src"), F.col("vlabel").alias("a")), "src").join(names.select(F.col("vid").alias("dst"), F.col("vlabel").alias("b")), "dst")
    return both.groupBy("a", "b").agg(F.count("*").alias("n"))


def _hop_sql(test: Callable[[str], str]) -> str:
    return " UNION ALL ".join(f"SELECT {o.text(u)} AS u, vid FROM hc WHERE vlabel={o.text(CLIQUE4.vertices[u])} AND {test(u)}" for u in sorted(CLIQUE4.vertices))


def _code_test(kind: str, want: list[int]) -> str:
    return f"({_code_sql(_prefix_sql(kind))}) >= {codes.ncode(want)}"


query(_HOPS + _hop_sql(lambda u: _code_test("s1_{0}+s2_{0}", CLIQUE4.ball(u, 2))), "f_ball")(lambda spark, d: filters.candidates(_hops(spark, d), CLIQUE4, filters.ball(2)))
query(_HOPS + _hop_sql(lambda u: _code_test("s1_{0}", CLIQUE4.ball(u, 1)) + " AND " + _code_test("s1_{0}+s2_{0}", CLIQUE4.ball(u, 2))), "f_nested_balls")(lambda spark, d: filters.candidates(_hops(spark, d), CLIQUE4, filters.nested_balls(2)))
query(_HOPS + _hop_sql(lambda u: _code_test("s1_{0}", CLIQUE4.ball(u, 1, True)) + " AND " + _code_test("s2_{0}", CLIQUE4.ball(u, 2, True))), "f_shell_optin")(lambda spark, d: filters.candidates(_hops(spark, d), CLIQUE4, filters.shell(2)))


def _sum(kind: str) -> str:
    return "+".join(kind.format(k) for k in range(1, 5))


query(_HOPS + _hop_sql(lambda u: f"({_sum('s1_{0}')}) >= {sum(CLIQUE4.ball(u, 1, True))} AND ({_sum('s2_{0}')}) >= {sum(CLIQUE4.ball(u, 2, True))}"), "f_shell_degree")(lambda spark, d: filters.candidates(_hops(spark, d), CLIQUE4, filters.shell(2, degree_only=True)))


def _packed_sql() -> str:
    one, two = _code_sql(_prefix_sql("s1_{0}")), _code_sql(_prefix_sql("s2_{0}"))
    pack = _code_sql(["c1", "c1+c2"])
    base = _HOPS.rstrip() + f", pc AS (SELECT vid, vlabel, {one} AS c1, {two} AS c2 FROM hc), hp AS (SELECT vid, vlabel, {pack} AS packed FROM pc) "
    return base + " UNION ALL ".join(f"SELECT {o.text(u)} AS u, vid FROM hp WHERE vlabel={o.text(CLIQUE4.vertices[u])} AND packed >= {codes.ncode([codes.ncode(CLIQUE4.ball(u, h, True)) for h in (1, 2)])}" for u in sorted(CLIQUE4.vertices))


query(_packed_sql(), "f_shell_packed")(lambda spark, d: filters.candidates(_hops(spark, d), CLIQUE4, filters.shell_packed(2)))


def _edge_aware_sql() -> str:
    out = []
    for u in sorted(RELATIONS.vertices):
        e = filters.edge_vectors(RELATIONS, u, _REL)[0]
        same = " AND ".join([*(f"x{k}={n}" for k, n in enumerate(RELATIONS.vector(u), 1)), *(f"e{k}={n}" for k, n in enumerate(e, 1))])
        out.append(f"SELECT {o.text(u)} AS u, vid FROM fe WHERE vlabel={o.text(RELATIONS.vertices[u])} AND (pdeg>{RELATIONS.pdeg(u)} OR (pdeg={RELATIONS.pdeg(u)} AND {same}))")
    return " UNION ALL ".join(out)


for _p in (False, True):
    query(_FE + _edge_aware_sql(), "f_edge_aware_packed" if _p else "f_edge_aware")(lambda spark, d, p=_p: filters.candidates(filters.one_hop(filters.start(view(spark, d, "T"), RELATIONS), _REL), RELATIONS, filters.edge_aware(_REL, packed=p)))


def _directed_sql() -> str:
    parts = []
    for u in sorted(DIRPATH.vertices):
        parts.append(f"SELECT {o.text(u)} AS u, vid FROM f WHERE {o.test(DIRPATH, u, 'edges', ['<1d'])}")
    return o.with_(o.graph("E", True), o.pruned(DIRPATH), o.counts(DIRPATH, elabels=["<1d"])) + " UNION ALL ".join(parts)


@query(_directed_sql())
def f_directed(spark, d):
    s = filters.start(view(spark, d, "E"), DIRPATH)
    test, names = filters.code_for(DIRPATH)
    return filters.candidates(filters.one_hop(s, names), DIRPATH, test)


# ---- peeling --------------------------------------------------------------------------------------------------------


def peeled(spark, d, q: Pattern, name: str = "T", engine: str = "frontier", **options) -> fixpoint.Peeled:
    return fixpoint.peel(filters.start(view(spark, d, name), q), q, engine=engine, **options)


def _peel_sql(q: Pattern, rounds: int, kind: str = "strict") -> str:
    return o.with_(o.graph("T"), o.pruned(q), o.peel(q, rounds, kind))


query(_peel_sql(TAILED, 1) + "SELECT vid, vlabel FROM k0", "peel_round1")(lambda spark, d: peeled(spark, d, TAILED, max_rounds=1).state.select("vid", "vlabel"))
query(_peel_sql(TRIANGLE, 4) + "SELECT vid, vlabel FROM k3", "peel_fixpoint_tri")(lambda spark, d: peeled(spark, d, TRIANGLE).state.select("vid", "vlabel"))
query(_peel_sql(TAILED, 5) + "SELECT vid, vlabel FROM k4", "peel_fixpoint_tailed")(lambda spark, d: peeled(spark, d, TAILED).state.select("vid", "vlabel"))
query(_peel_sql(TAILED, 5) + "SELECT vid, vlabel FROM k4", "peel_full_rescan")(lambda spark, d: peeled(spark, d, TAILED, engine="full").state.select("vid", "vlabel"))
query(_peel_sql(TAILED, 5) + "SELECT vid, vlabel FROM k4", "peel_auto")(lambda spark, d: peeled(spark, d, TAILED, engine="auto").state.select("vid", "vlabel"))
query(_peel_sql(TAILED, 5, "nlf") + "SELECT vid, vlabel FROM k4", "peel_nlf")(lambda spark, d: peeled(spark, d, TAILED, test=filters.nlf).state.select("vid", "vlabel"))
query(_peel_sql(TAILED, 5) + "SELECT vlabel, count(*) AS n FROM k4 GROUP BY 1", "peel_kept_by_label")(lambda spark, d: peeled(spark, d, TAILED).state.groupBy("vlabel").agg(F.count("*").alias("n")))


def _edge_peel_sql(name: str, q: Pattern, rounds: int) -> str:
    return o.with_(o.graph(name, q.directed), o.pruned(q), o.peel(q, rounds, "edges", filters.edge_labels(q))) + f"SELECT vid, vlabel FROM k{rounds - 1}"


def _edge_peel(spark, d, name: str, q: Pattern) -> DataFrame:
    test, names = filters.code_for(q)
    return peeled(spark, d, q, name, test=test, elabels=names).state.select("vid", "vlabel")


query(_edge_peel_sql("T", RELATIONS, 4), "peel_edge_aware")(lambda spark, d: _edge_peel(spark, d, "T", RELATIONS))
query(_edge_peel_sql("D", FLAGGED, 4), "peel_edge_flagged")(lambda spark, d: _edge_peel(spark, d, "D", FLAGGED))
query(_edge_peel_sql("E", DIRPATH, 5), "peel_directed")(lambda spark, d: _edge_peel(spark, d, "E", DIRPATH))


def _log_sql(q: Pattern, rounds: int) -> str:
    fails = [f"SELECT {r + 1} AS round, count(*) AS removed, count(*) FILTER (WHERE NOT coalesce({o.some(q, 'degree')}, false)) AS by_degree FROM f{r} WHERE NOT ({o.some(q, 'strict')})" for r in range(rounds)]
    return _peel_sql(q, rounds) + f"SELECT round::INTEGER AS round, removed, by_degree, removed-by_degree AS by_code FROM ({' UNION ALL '.join(fails)}) WHERE removed > 0"


@query(_log_sql(TAILED, 5))
def peel_round_log(spark, d):
    return measures.round_log(spark, peeled(spark, d, TAILED)).select("round", "removed", "by_degree", "by_code")


@query()
def peel_touched(spark, d):
    """Vertices looked at in each round: the frontier's, where a full rescan looks at all that are left."""
    return measures.round_log(spark, peeled(spark, d, TAILED))


# ---- matches --------------------------------------------------------------------------------------------------------

for _name, (_g, _q) in FIXED.items():
    query(o.embeddings(_g, _q), f"m_{_name}")(lambda spark, d, g=_g, q=_q: match(view(spark, d, g), q).embeddings)

query(o.embeddings("T", TRIANGLE), "m_dfs_triangle")(lambda spark, d: match(view(spark, d, "T"), TRIANGLE, engine="dfs").embeddings)
query(o.embeddings("T", TAILED), "m_edge_pass")(lambda spark, d: match(view(spark, d, "T"), TAILED, access="pass").embeddings)
query(o.embeddings("T", TAILED), "m_local_only")(lambda spark, d: match(view(spark, d, "T"), TAILED, max_rounds=1).embeddings)
for _how in search.ORDERS:
    query(o.embeddings("T", TAILED), f"m_order_{_how}")(lambda spark, d, h=_how: match(view(spark, d, "T"), TAILED, how=h).embeddings)
query(o.embeddings("T", SAME), "m_merged_equivalents")(lambda spark, d: search.joins_merged(*_parts(spark, d, "T", SAME), SAME, simple=True))
query(o.embeddings("T", ABSENT), "m_absent_label")(lambda spark, d: match(view(spark, d, "T"), ABSENT).embeddings)
query(o.embeddings("T", STAR3, "count(*) AS n"), "m_count_only")(lambda spark, d: count(view(spark, d, "T"), STAR3))
query(o.embeddings("T", TAILED, "count(*) AS n"), "m_count_tailed")(lambda spark, d: count(view(spark, d, "T"), TAILED))
query(o.embeddings("T", APART, "count(*) AS n"), "m_disconnected_count")(lambda spark, d: count(view(spark, d, "T"), APART))
query(o.embeddings("T", SAME) + " AND v_a.vid < v_b.vid", "m_unique_subgraphs")(lambda spark, d: match(view(spark, d, "T"), SAME, unique="subgraph").embeddings)
query(o.embeddings("T", TRIANGLE, "DISTINCT [v_o.vid, v_p.vid, v_s.vid]::VARCHAR AS embedding"), "m_as_arrays")(lambda spark, d: search.as_arrays(match(view(spark, d, "T"), TRIANGLE).embeddings).select(F.concat(F.lit("["), F.array_join("embedding", ", "), F.lit("]")).alias("embedding")))


@query(o.embeddings("T", TRIANGLE))
def m_sql_text(spark, d):
    register_views(view(spark, d, "T"))
    return match_sql(spark, "(o:O:1-URGENT)-(p:P:PROMO), (o)-(s:S:ASIA), (p)-(s)")


@query(f"SELECT (count(*) > 0) AS found FROM ({o.embeddings('T', TRIANGLE)})")
def m_exists(spark, d):
    return match(view(spark, d, "T"), TRIANGLE).embeddings.limit(1).agg((F.count("*") > 0).alias("found"))


def _parts(spark, d, name: str, q: Pattern) -> tuple[DataFrame, DataFrame]:
    p = peeled(spark, d, q, name)
    return p.adj, cut(fixpoint.candidate_sets(p, q), "cand")


# ---- baselines ------------------------------------------------------------------------------------------------------

for _b in ("brute", "degree_only", "nlf", "mnd_nlf", "refined"):
    query(o.embeddings("T", TAILED), f"b_{_b}")(lambda spark, d, b=_b: getattr(baselines, b)(view(spark, d, "T"), TAILED))
query(o.embeddings("T", TAILED), "b_tree_index_match")(lambda spark, d: baselines.tree_index_match(baselines.tree_index(view(spark, d, "T"), TAILED), TAILED))
query(o.embeddings("D", SQUARE), "b_tree_index_square")(lambda spark, d: baselines.tree_index_match(baselines.tree_index(view(spark, d, "D"), SQUARE), SQUARE))


def _refine_sql(q: Pattern, levels: int) -> str:
    parts = [f"c0 AS ({o.candidates(q, 'degree')})"]
    for r in range(levels):
        each = []
        for u in sorted(q.vertices):
            near = " ".join(f"AND EXISTS (SELECT 1 FROM la a JOIN c{r} w ON w.vid=a.dst AND w.u={o.text(w)} WHERE a.src=c.vid)" for w in sorted(set(q.neighbours(u))))
            each.append(f"SELECT u, vid FROM c{r} c WHERE u={o.text(u)} {near}")
        parts.append(f"c{r + 1} AS MATERIALIZED ({' UNION ALL '.join(each)})")
    return o.with_(o.graph("T"), o.pruned(q), o.counts(q), *parts) + f"SELECT u, vid FROM c{levels}"


query(_refine_sql(TAILED, 2), "b_refine_levels2")(lambda spark, d: baselines.refine(view(spark, d, "T"), TAILED, levels=2))
query(_refine_sql(TAILED, 6), "b_refine")(lambda spark, d: baselines.refine(view(spark, d, "T"), TAILED))


@query()
def b_tree_index_rows(spark, d):
    return baselines.tree_index(view(spark, d, "T"), TAILED).rows()


@query("SELECT * FROM (VALUES ('dfs', 0::BIGINT, 0::BIGINT), ('lookahead', 0, 0), ('merged', 0, 0), ('nlf', 0, 0), ('pass', 0, 0), ('tree_index', 0, 0)) t(other, only_a, only_b)")
def b_agreement(spark, d):
    """Rows that only one of two matchers finds, for each of the others against the joins after peeling."""
    g = view(spark, d, "T")
    adj, cand = _parts(spark, d, "T", TAILED)
    own = match(g, TAILED).embeddings
    others = {
        "dfs": search.dfs(adj, cand, TAILED), "lookahead": search.dfs(adj, cand, TAILED, lookahead=True), "merged": search.joins_merged(adj, cand, TAILED, simple=True),
        "nlf": baselines.nlf(g, TAILED), "pass": match(g, TAILED, access="pass").embeddings, "tree_index": baselines.tree_index_match(baselines.tree_index(g, TAILED), TAILED),
    }
    out = None
    for name, rows in others.items():
        one = same_rows(own, rows).select(F.lit(name).alias("other"), "only_a", "only_b")
        out = one if out is None else out.union(one)
    return out


# ---- edge pass and streams --------------------------------------------------------------------------------------------

_PASS = o.features("T", TAILED) + f", kept AS (SELECT vid, vlabel FROM f WHERE {o.some(TAILED, 'strict')}) "
query(_PASS + "SELECT vid, vlabel FROM kept", "s_group_pass_kept")(lambda spark, d: edgepass.prefilter(filters.start(view(spark, d, "T"), TAILED), TAILED).vertices.select("vid", "vlabel"))
query(_PASS + "SELECT src, dst, elabel FROM la WHERE src IN (SELECT vid FROM kept) AND dst IN (SELECT vid FROM kept)", "s_sorted_pass_kept")(lambda spark, d: edgepass.sorted_pass(filters.start(view(spark, d, "T"), TAILED), TAILED))


@query(_PASS.replace(o.triple(TAILED), "true") + "SELECT vid FROM kept")
def s_random_pass_kept(spark, d):
    g = view(spark, d, "T")
    return edgepass.random_pass(g.edges, g.vertices, TAILED)[0]


@query()
def s_random_pass_held(spark, d):
    g = view(spark, d, "T")
    return spark.createDataFrame(edgepass.random_pass(g.edges, g.vertices, TAILED)[1], "batch int, vertices long, edges long")


_EV = "SELECT event_type, epoch_us(ts) AS us FROM events"


@query(f"WITH e AS ({_EV}) SELECT (us // 21600000000 * 21600)::BIGINT AS start_s, event_type, count(*) AS n FROM e GROUP BY 1, 2")
def s_window_tumbling(spark, d):
    out = edgepass.run_to_memory(edgepass.windowed_counts(edgepass.event_stream(spark, d), "6 hours"), "s_tumbling")
    return out.select(F.unix_seconds("window.start").alias("start_s"), "event_type", "n")


@query(f"WITH e AS ({_EV}), w AS (SELECT event_type, us // 10800000000 * 10800 - unnest([0, 10800]) AS s FROM e) SELECT s::BIGINT AS start_s, event_type, count(*) AS n FROM w GROUP BY 1, 2")
def s_window_sliding(spark, d):
    out = edgepass.run_to_memory(edgepass.windowed_counts(edgepass.event_stream(spark, d), "6 hours", "3 hours"), "s_sliding")
    return out.select(F.unix_seconds("window.start").alias("start_s"), "event_type", "n")


@query("""WITH g AS (SELECT user_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w <= 7200000000 THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
    s AS (SELECT user_id, us, sum(fresh) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS k FROM g)
    SELECT user_id, min(us)::BIGINT AS start_us, count(*) AS n FROM s GROUP BY user_id, k""")
def s_session(spark, d):
    """A session is sent once, when the watermark has passed it; the end mark makes it pass the last ones."""
    out = edgepass.run_to_files(edgepass.sessions(edgepass.ended(edgepass.event_stream(spark, d)), "2 hours"), "s_sessions")
    return out.select("user_id", F.unix_micros("window.start").alias("start_us"), "n")


@query("SELECT DISTINCT user_id, event_type FROM events")
def s_dedup(spark, d):
    return edgepass.run_to_files(edgepass.event_stream(spark, d).select("user_id", "event_type").dropDuplicates(), "s_dedup")


_LIVE = o.with_(o.graph("T"), f"lv AS (SELECT * FROM v WHERE vlabel IN ({', '.join(map(o.text, TAILED.labels))}))", "la AS (SELECT a.*, d.vlabel AS dlabel FROM adj a JOIN lv s ON s.vid=a.src JOIN lv d ON d.vid=a.dst WHERE a.elabel IN ('placed'))", o.counts(TAILED))


@query(_LIVE + "SELECT vid, x1, x2, x3, x4, pdeg FROM f WHERE pdeg > 0")
def s_live_counts(spark, d):
    """Orders as a stream of placed edges; the counts after the last of them."""
    g = view(spark, d, "T")
    out = edgepass.run_to_memory(edgepass.live_counts(live.order_stream(spark, d), g.vertices, TAILED), "s_live")
    return out.select("vid", "x1", "x2", "x3", "x4", "pdeg")


@query(f"SELECT {2 * o.SPACE}+o_orderkey AS vid, count(*) AS n FROM orders GROUP BY 1")
def s_live_state(spark, d):
    """The same with state of its own for each vertex, which seals it after a while without edges."""
    out = edgepass.run_to_files(live.stateful_counts(live.order_stream(spark, d)), "s_live_state")
    return out.groupBy("vid").agg(F.max("n").alias("n"))


@query(_LIVE + f"SELECT vid, pdeg, {o.some(TAILED, 'strict')} AS keep FROM f WHERE pdeg > 0")
def s_live_filter(spark, d):
    """Each vertex's last word on the stream of placed edges: kept as soon as it passes, dropped when it is sealed."""
    g = view(spark, d, "T")
    out = edgepass.run_to_files(live.live_filter(live.order_stream(spark, d), g.vertices, TAILED, idle="1 day"), "s_live_filter")
    return out.groupBy("vid").agg(F.max("pdeg").alias("pdeg"), F.max_by("keep", "pdeg").alias("keep"))


@query("SELECT o.o_orderkey AS order_id, c.c_mktsegment AS segment FROM orders o JOIN customer c ON o.o_custkey = c.c_custkey")
def s_join_static(spark, d):
    """A stream joined with a table that stands still."""
    out = live.order_stream(spark, d).join(graphs.table(spark, d, "customer").select(graphs.vid("customer", "c_custkey").alias("src"), "c_mktsegment"), "src")
    rows = edgepass.run_to_files(out.select((F.col("dst") - 2 * o.SPACE).alias("order_id"), F.col("c_mktsegment").alias("segment")), "s_join_static")
    return rows


@query("SELECT v.event_id AS view_id, c.event_id AS click_id FROM events v JOIN events c ON v.user_id = c.user_id AND v.event_type = 'view' AND c.event_type = 'click' AND c.ts >= v.ts AND c.ts <= v.ts + INTERVAL 2 HOURS")
def s_join_streams(spark, d):
    """Two streams joined within an interval; rows older than the watermark leave the state."""
    return edgepass.run_to_files(edgepass.followed_by(edgepass.event_stream(spark, d), "view", "click", "2 hours"), "s_join_streams")


# ---- graph databases ------------------------------------------------------------------------------------------------

_ROLES = ["assistant", "system", "user"]


_CONV = """WITH t AS (SELECT conv_id, role, lag(role) OVER w AS p, lead(role) OVER w AS q FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
    x AS (SELECT conv_id, CASE role WHEN 'assistant' THEN 1 WHEN 'system' THEN 2 WHEN 'user' THEN 3 ELSE 0 END AS r, (coalesce(p='assistant', false)::INT + coalesce(q='assistant', false)::INT)::HUGEINT AS x1,
      (coalesce(p='system', false)::INT + coalesce(q='system', false)::INT)::HUGEINT AS x2, (coalesce(p='user', false)::INT + coalesce(q='user', false)::INT)::HUGEINT AS x3 FROM t),
    c AS (SELECT conv_id, r, x1 + (x1+x2)*(x1+x2+1)//2 + (x1+x2+x3)*(x1+x2+x3+1)*(x1+x2+x3+2)//6 AS code FROM x),
    k AS (SELECT conv_id AS graph_id, count(*) AS n_vertices, string_agg((r + (r+code)*(r+code+1)//2)::VARCHAR, ',' ORDER BY r + (r+code)*(r+code+1)//2) AS codes FROM c GROUP BY 1) """


@query(_CONV + "SELECT graph_id, n_vertices, codes FROM k")
def x_conversation_codes(spark, d):
    """Each graph's vertex codes with labels folded in, sorted: what its graph code is made of."""
    coded = gindex.vertex_codes(*graphs.conversation_graphs(spark, d), _ROLES)
    sorted_ = F.sort_array(F.collect_list("own"))  # turns of one conversation
    return coded.groupBy("graph_id").agg(F.count("*").alias("n_vertices"), sorted_.alias("c")).select("graph_id", "n_vertices", F.array_join(F.transform("c", lambda x: x.cast("string")), ",").alias("codes"))


@query()
def x_conversation_digests(spark, d):
    """The graph codes themselves, as digits and digest; tests hold them against plain integers."""
    return gindex.graph_codes(gindex.vertex_codes(*graphs.conversation_graphs(spark, d), _ROLES))


@query(_CONV + "SELECT a.graph_id FROM k a JOIN k b USING (codes) WHERE b.graph_id = (SELECT min(graph_id) FROM k)")
def x_lookup(spark, d):
    """The conversations that have the graph code of the first one, found by digest."""
    v, e = graphs.conversation_graphs(spark, d)
    coded = cut(gindex.vertex_codes(v, e, _ROLES), "coded")
    first = coded.agg(F.min("graph_id").alias("graph_id"))
    wanted = gindex.graph_codes(coded.join(F.broadcast(first), "graph_id")).first()["digest"]
    return gindex.lookup(coded, wanted)


@query(_CONV + "SELECT count(DISTINCT codes) AS digests, 0::BIGINT AS shared, count(DISTINCT codes) AS signatures FROM k")
def x_digest_collisions(spark, d):
    return gindex.collisions(cut(gindex.vertex_codes(*graphs.conversation_graphs(spark, d), _ROLES), "coded"))


@query("""WITH t AS (SELECT conv_id, turn, role, lag(role) OVER w AS p, lead(role) OVER w AS q FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
    k AS (SELECT conv_id, string_agg(role||':'||least(coalesce(p,''),coalesce(q,''))||greatest(coalesce(p,''),coalesce(q,'')), ',' ORDER BY role||':'||least(coalesce(p,''),coalesce(q,''))||greatest(coalesce(p,''),coalesce(q,''))) AS sig FROM t GROUP BY 1)
    SELECT count(*) AS n FROM k GROUP BY sig""")
def x_equal_conversations(spark, d):
    coded = gindex.vertex_codes(*graphs.conversation_graphs(spark, d), _ROLES)
    return gindex.equal_groups(coded).select("n")


_CHAIN = parse("(a:user)-(b:assistant)-(c:user)")


@query("""WITH t AS (SELECT conv_id, role, lag(role) OVER w AS p, lead(role) OVER w AS q FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn))
    SELECT conv_id AS graph_id, (2*count(*))::BIGINT AS n FROM t WHERE role='assistant' AND p='user' AND q='user' GROUP BY 1""")
def x_conversation_containment(spark, d):
    return gindex.containment(*graphs.conversation_graphs(spark, d), _CHAIN)


@query(f"WITH g AS ({o.embeddings('T', TRIANGLE)}), s AS (SELECT DISTINCT l_orderkey, l_partkey, l_suppkey FROM lineitem), a AS (SELECT DISTINCT l_orderkey k, l_suppkey s FROM lineitem), b AS (SELECT DISTINCT l_orderkey k, l_partkey p FROM lineitem) SELECT l_orderkey AS graph_id, count(*) AS n FROM s JOIN g ON g.m_o={2 * o.SPACE}+l_orderkey AND g.m_p={3 * o.SPACE}+l_partkey AND g.m_s={4 * o.SPACE}+l_suppkey GROUP BY 1")
def x_order_containment(spark, d):
    return gindex.containment(*graphs.order_graphs(spark, d), TRIANGLE)


# ---- measures -------------------------------------------------------------------------------------------------------


@query(o.features("T", TAILED) + f", c AS ({o.candidates(TAILED, 'strict')}) SELECT u, count(*) AS n, round(log10(count(*)), 6) AS log10 FROM c GROUP BY 1")
def k_search_space(spark, d):
    return measures.search_space(filters.candidates(features(spark, d, "T", TAILED), TAILED, filters.code_strict))


def _pruned_sql() -> str:
    kinds = ("label", "degree", "mnd", "nlf", "mnd_nlf", "lemma", "strict")
    return o.with_(o.graph("T"), o.pruned(TAILED), o.counts(TAILED), o.mnd()) + " UNION ALL ".join(f"SELECT '{k}' AS filter, count(*) AS pairs, count(DISTINCT vid) AS vertices FROM ({o.candidates(TAILED, k, 'm')})" for k in kinds)


@query(_pruned_sql())
def k_pruned_per_filter(spark, d):
    return measures.pairs_per_filter(features(spark, d, "T", TAILED, True), TAILED)


def _precision_sql() -> str:
    images = " UNION ".join(f"SELECT '{u}' AS u, m_{u} AS vid FROM emb" for u in sorted(TAILED.vertices))
    return f"WITH emb AS ({o.embeddings('T', TAILED)}), img AS ({images}), cand AS ({o.features('T', TAILED) + o.candidates(TAILED, 'strict')}) SELECT c.u, count(*) AS candidates, count(i.vid) AS images, round(count(i.vid)/count(*), 6) AS precision_, (SELECT count(*) FROM img j WHERE j.u=c.u) AS all_images FROM cand c LEFT JOIN img i ON i.u=c.u AND i.vid=c.vid GROUP BY 1"


@query(_precision_sql())
def k_filter_precision(spark, d):
    cand = filters.candidates(features(spark, d, "T", TAILED), TAILED, filters.code_strict)
    return measures.precision(cand, match(view(spark, d, "T"), TAILED).embeddings)


@query(_F3 + f", c AS (SELECT DISTINCT x1, x2, x3, ({_code_sql(_SUMS[:3])}) AS code FROM f), n AS (SELECT code, count(*) AS n FROM c GROUP BY 1) SELECT 'code' AS code, count(*) FILTER (WHERE n > 1) AS collisions FROM n")
def k_collisions(spark, d):
    """Codes that several neighbourhoods share: none for codes of one length."""
    f = features(spark, d, "T", TRIANGLE)
    return measures.collisions(f, codes.ncode_column(_xs(TRIANGLE)), ["x1", "x2", "x3"]).select(F.lit("code").alias("code"), F.col("collisions"))


@query()
def k_log_collisions(spark, d):
    return measures.collisions(features(spark, d, "T", TRIANGLE), codes.ncode_log(_xs(TRIANGLE)), ["x1", "x2", "x3"])


@query(_F3 + f", c AS (SELECT ({_code_sql(_SUMS[:3])}) AS code FROM f) SELECT length(code::VARCHAR) AS digits, count(*) AS n FROM c GROUP BY 1")
def k_code_digits(spark, d):
    return measures.digits(features(spark, d, "T", TRIANGLE).select(codes.ncode_column(_xs(TRIANGLE)).alias("code")))


@query()
def k_memory(spark, d):
    """Rows that the method keeps, and that the tree index stores."""
    return measures.stored(spark, view(spark, d, "T"), TAILED)


@query()
def k_shell_loss(spark, d):
    """Images that the exact-hop filter loses and the ball filters keep: why it is opt-in."""
    emb = match(view(spark, d, "Y"), CLIQUE4).embeddings
    f = _hops(spark, d)
    out = None
    for name, test in (("ball", filters.ball(2)), ("nested_balls", filters.nested_balls(2)), ("shell", filters.shell(2))):
        one = measures.recall(filters.candidates(f, CLIQUE4, test), emb).select(F.lit(name).alias("filter"), "images", "kept")
        out = one if out is None else out.union(one)
    return out


# ---- experiment workloads -------------------------------------------------------------------------------------------

#: Patterns that workloads.walk() has drawn (two a size, seed 42) from each graph at sf0.01, by graph, kind and size.
WALKED: dict[str, list[str]] = {
    "D_sparse_3": [
        "(u0:Brand#7)-(u1:N9), (u2:Brand#21)-(u1:N9)",
        "(u2:Brand#24)-(u1:N6), (u0:Brand#16)-(u1:N6)",
    ],
    "D_sparse_4": [
        "(u0:Brand#7)-(u1:N9), (u2:Brand#21)-(u3:N11), (u2:Brand#21)-(u1:N9)",
        "(u2:Brand#24)-(u3:N17), (u2:Brand#24)-(u1:N6), (u0:Brand#16)-(u1:N6)",
    ],
    "D_dense_3": [
        "(u2:Brand#4)-(u1:N19), (u0:Brand#7)-(u1:N19)",
        "(u2:Brand#1)-(u1:N7), (u0:Brand#16)-(u1:N7)",
    ],
    "D_dense_4": [
        "(u2:Brand#4)-(u3:N8), (u2:Brand#4)-(u1:N19), (u0:Brand#7)-(u1:N19)",
        "(u2:Brand#1)-(u3:N16), (u2:Brand#1)-(u1:N7), (u0:Brand#16)-(u1:N7)",
    ],
    "Y_sparse_3": [
        "(u1:Brand#7/2)-(u0:Brand#7/2), (u1:Brand#7/2)-(u2:Brand#18/2)",
        "(u1:Brand#8/2)-(u2:Brand#12/0), (u1:Brand#8/2)-(u0:Brand#16/1)",
    ],
    "Y_sparse_5": [
        "(u3:Brand#21/2)-(u2:Brand#18/2), (u3:Brand#21/2)-(u4:Brand#13/0), (u1:Brand#7/2)-(u0:Brand#7/2), (u1:Brand#7/2)-(u2:Brand#18/2)",
        "(u4:Brand#16/2)-(u3:Brand#8/2), (u3:Brand#8/2)-(u2:Brand#12/0), (u1:Brand#8/2)-(u2:Brand#12/0), (u1:Brand#8/2)-(u0:Brand#16/1)",
    ],
    "Y_dense_3": [
        "(u0:Brand#7/2)-(u1:Brand#16/2), (u1:Brand#16/2)-(u2:Brand#15/1)",
        "(u2:Brand#2/0)-(u1:Brand#16/1), (u1:Brand#16/1)-(u0:Brand#16/1)",
    ],
    "Y_dense_5": [
        "(u4:Brand#2/1)-(u3:Brand#18/1), (u0:Brand#7/2)-(u1:Brand#16/2), (u3:Brand#18/1)-(u2:Brand#15/1), (u1:Brand#16/2)-(u2:Brand#15/1)",
        "(u2:Brand#2/0)-(u1:Brand#16/1), (u2:Brand#2/0)-(u3:Brand#15/1), (u1:Brand#16/1)-(u0:Brand#16/1), (u4:Brand#2/1)-(u3:Brand#15/1)",
    ],
    "H_sparse_3": [
        "(u1:Brand#7/MEDIUM)-(u2:N19/AUTOMOBILE), (u1:Brand#7/MEDIUM)-(u0:N13/BUILDING)",
        "(u1:Brand#2/LARGE)-(u2:N1/BUILDING), (u1:Brand#2/LARGE)-(u0:N2/FURNITURE)",
    ],
    "H_sparse_5": [
        "(u3:Brand#1/MEDIUM)-(u2:N19/AUTOMOBILE), (u3:Brand#1/MEDIUM)-(u4:N0/MACHINERY), (u1:Brand#7/MEDIUM)-(u2:N19/AUTOMOBILE), (u1:Brand#7/MEDIUM)-(u0:N13/BUILDING)",
        "(u3:Brand#11/SMALL)-(u2:N1/BUILDING), (u3:Brand#11/SMALL)-(u4:N13/MACHINERY), (u1:Brand#2/LARGE)-(u2:N1/BUILDING), (u1:Brand#2/LARGE)-(u0:N2/FURNITURE)",
    ],
    "H_dense_3": [
        "(u1:Brand#20/PROMO)-(u0:N13/BUILDING), (u1:Brand#20/PROMO)-(u2:N23/HOUSEHOLD)",
        "(u1:Brand#6/ECONOMY)-(u0:N2/FURNITURE), (u1:Brand#6/ECONOMY)-(u2:N6/MACHINERY)",
    ],
    "H_dense_5": [
        "(u3:Brand#2/STANDARD)-(u4:N16/AUTOMOBILE), (u3:Brand#2/STANDARD)-(u2:N23/HOUSEHOLD), (u1:Brand#20/PROMO)-(u0:N13/BUILDING), (u1:Brand#20/PROMO)-(u2:N23/HOUSEHOLD)",
        "(u3:Brand#2/SMALL)-(u4:N9/HOUSEHOLD), (u3:Brand#2/SMALL)-(u2:N6/MACHINERY), (u1:Brand#6/ECONOMY)-(u0:N2/FURNITURE), (u1:Brand#6/ECONOMY)-(u2:N6/MACHINERY)",
    ],
}


def walked(name: str, kind: str) -> dict[str, Pattern]:
    """The drawn patterns of a graph and kind: size/number to pattern."""
    found = {}
    for key, texts in WALKED.items():
        g, k, size = key.split("_")
        if (g, k) == (name, kind):
            found |= {f"{size}/{n}": parse(t) for n, t in enumerate(texts)}
    return found


def _walked_sql(name: str, kind: str) -> str:
    each = [f"SELECT {o.text(key)} AS pattern, n AS codes, n AS nlf, n AS tree_index FROM ({o.embeddings(name, q, 'count(*) AS n')})" for key, q in walked(name, kind).items()]
    return " UNION ALL ".join(each)


for _n, _full in (("D", "dense"), ("Y", "fewlabel"), ("H", "manylabel")):
    for _k in ("sparse", "dense"):
        query(_walked_sql(_n, _k), f"w_{_k}_{_full}")(lambda spark, d, n=_n, k=_k: workloads.fixed_set(view(spark, d, n), walked(n, k)))


def _pruning_sql() -> str:
    kinds, parts = ("label", "degree", "mnd", "nlf", "mnd_nlf", "lemma", "strict"), []
    for q in walked("Y", "sparse").values():
        base = o.with_(o.graph("Y"), o.pruned(q), o.counts(q), o.mnd())
        parts += [f"SELECT * FROM ({base} SELECT '{k}' AS filter, count(*) AS pairs, count(DISTINCT vid) AS vertices FROM ({o.candidates(q, k, 'm')}))" for k in kinds]
        peel_ = o.with_(o.graph("Y"), o.pruned(q), o.peel(q, 9))
        parts.append(f"SELECT * FROM ({peel_} SELECT 'peel' AS filter, count(*) AS pairs, count(DISTINCT vid) AS vertices FROM ({o.candidates(q, 'strict', 'f8')}))")
    return f"SELECT filter, sum(pairs)::BIGINT AS pairs, sum(vertices)::BIGINT AS vertices FROM ({' UNION ALL '.join(parts)}) GROUP BY 1"


@query(_pruning_sql())
def w_pruning_fewlabel(spark, d):
    """What each filter leaves, one shot, and what peeling leaves, summed over the sparse patterns of Y."""
    return workloads.pruning(view(spark, d, "Y"), list(walked("Y", "sparse").values()))


@query()
def w_memory(spark, d):
    """Bytes written by the own method and by the tree index, and by index tables alone, for the sparse patterns of each graph."""
    rows = []
    for name in "DYH":
        g = view(spark, d, name)
        for key, q in walked(name, "sparse").items():
            if key.endswith("/0"):
                for r in measures.stored(spark, g, q).collect():
                    rows.append((name, int(key.split("/")[0]), r["engine"], r["vertices"], r["edge_rows"], r["bytes"]))
    return spark.createDataFrame(rows, "graph string, size int, engine string, vertices long, edge_rows long, bytes long")


@query()
def w_random_pass_held(spark, d):
    """Edges and vertices that a random-arrival pass holds at its end, by pattern size."""
    g = view(spark, d, "T")
    rows = [(len(q.vertices), e["vertices"], e["edges"]) for q in (EDGE, PATH3, TAILED) for e in edgepass.random_pass(g.edges, g.vertices, q)[1][-1:]]
    return spark.createDataFrame(rows, "size int, vertices long, edges long")


@query(" UNION ALL ".join(f"SELECT '{n}' AS pattern_id, (SELECT count(*) FROM ({o.embeddings('T', q)})) AS n" for n, q in (("edge", EDGE), ("path3", PATH3), ("triangle", TRIANGLE))))
def m_run_set(spark, d):
    """Several patterns over one graph that is read once."""
    return run_set(view(spark, d, "T"), {"edge": EDGE, "path3": PATH3, "triangle": TRIANGLE}).select("pattern_id", "n")


def queries() -> dict[str, Query]:
    return {n: f for n, (f, _) in _REGISTERED.items()}


def oracle_sql() -> dict[str, str]:
    return {n: s for n, (_, s) in _REGISTERED.items() if s}


__all__ = ["FIXED", "Window", "oracle_sql", "queries"]
