"""Graph views over the given tables. A vid is kind * 10^14 + key, so all tables share one id space."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators.graph import LabeledGraph
from .tables import table

KIND = {"customer": 1, "orders": 2, "part": 3, "supplier": 4, "event": 5, "user": 6, "document": 7, "vector": 8, "page": 9, "turn": 10}
SPACE = 10**14


def vid(kind: str, key: str | Column) -> Column:
    return (F.lit(KIND[kind] * SPACE) + (F.col(key) if isinstance(key, str) else key)).cast("long")


def _edges(df: DataFrame, a: Column, b: Column, label: str | Column | None) -> DataFrame:
    e = F.lit(label).cast("string") if label is None or isinstance(label, str) else label
    return df.select(a.alias("src"), b.alias("dst"), e.alias("elabel")).distinct()


def trade(spark: SparkSession, sf_dir: str, directed: bool = False) -> LabeledGraph:
    """T: customers, orders, parts and suppliers, joined by who placed, contains, was sourced from, supplies."""
    c, o, p, s = (table(spark, sf_dir, n) for n in ("customer", "orders", "part", "supplier"))
    region = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    s = s.join(region, F.col("s_nationkey") == F.col("n_nationkey"))
    vertices = c.select(vid("customer", "c_custkey").alias("vid"), F.concat(F.lit("C:"), "c_mktsegment").alias("vlabel"))
    vertices = vertices.union(o.select(vid("orders", "o_orderkey"), F.concat(F.lit("O:"), "o_orderpriority")))
    vertices = vertices.union(p.select(vid("part", "p_partkey"), F.concat(F.lit("P:"), "p_type")))
    vertices = vertices.union(s.select(vid("supplier", "s_suppkey"), F.concat(F.lit("S:"), "r_name")))
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    order, part, supplier = vid("orders", "l_orderkey"), vid("part", "l_partkey"), vid("supplier", "l_suppkey")
    edges = o.select(vid("customer", "o_custkey").alias("src"), vid("orders", "o_orderkey").alias("dst"), F.lit("placed").alias("elabel"))
    edges = edges.union(_edges(li, order, part, "contains")).union(_edges(li, order, supplier, "sourced")).union(_edges(li, part, supplier, "supplies"))
    return LabeledGraph(vertices, edges, directed, simple=True)


def dense(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """D: parts by brand and suppliers by nation, joined where a supplier delivers a part; few vertices, many edges."""
    p, s, li = (table(spark, sf_dir, n) for n in ("part", "supplier", "lineitem"))
    vertices = p.select(vid("part", "p_partkey").alias("vid"), F.col("p_brand").alias("vlabel")).union(s.select(vid("supplier", "s_suppkey"), F.concat(F.lit("N"), F.col("s_nationkey").cast("string"))))
    edges = li.groupBy(vid("part", "l_partkey").alias("src"), vid("supplier", "l_suppkey").alias("dst")).agg(F.min("l_returnflag").alias("elabel"))
    return LabeledGraph(vertices, edges, simple=True)


def few_labels(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Y: parts, joined where one order returned both. An order has a few lines only, so the self-join stays small."""
    p, li = table(spark, sf_dir, "part"), table(spark, sf_dir, "lineitem")
    vertices = p.select(vid("part", "p_partkey").alias("vid"), F.concat("p_brand", F.lit("/"), (F.col("p_size") % 3).cast("string")).alias("vlabel"))
    returned = li.where("l_returnflag = 'R'").select("l_orderkey", vid("part", "l_partkey").alias("v")).distinct()
    pairs = returned.alias("a").join(returned.alias("b"), "l_orderkey").where("a.v < b.v")
    return LabeledGraph(vertices, _edges(pairs, F.col("a.v"), F.col("b.v"), None), simple=True)


def many_labels(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """H: parts by brand and type, orders by their customer's nation and segment, joined where an order has a part."""
    p, o, c, li = (table(spark, sf_dir, n) for n in ("part", "orders", "customer", "lineitem"))
    vertices = p.select(vid("part", "p_partkey").alias("vid"), F.concat("p_brand", F.lit("/"), "p_type").alias("vlabel"))
    placed = o.select("o_orderkey", "o_custkey").join(c.select("c_custkey", "c_nationkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
    vertices = vertices.union(placed.select(vid("orders", "o_orderkey"), F.concat(F.lit("N"), F.col("c_nationkey").cast("string"), F.lit("/"), "c_mktsegment")))
    return LabeledGraph(vertices, _edges(li, vid("part", "l_partkey"), vid("orders", "l_orderkey"), None), simple=True)


def event_succession(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """E, directed: each event and the same user's next one; edges labelled by the gap."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    after = e.select("event_id", F.lead("event_id").over(w).alias("next"), (F.lead(F.unix_micros("ts")).over(w) - F.unix_micros("ts")).alias("gap")).where("next is not null")
    label = F.when(F.col("gap") < 3_600_000_000, "<1h").when(F.col("gap") < 86_400_000_000, "<1d").otherwise(">=1d")
    edges = after.select(vid("event", "event_id").alias("src"), vid("event", "next").alias("dst"), label.alias("elabel"))
    return LabeledGraph(e.select(vid("event", "event_id").alias("vid"), F.col("event_type").alias("vlabel")), edges, directed=True, simple=True)


def conversation_graphs(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """C, a database of small graphs: (graph_id, vid, vlabel) turns by role, (graph_id, src, dst, elabel) turns that follow."""
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    at = vid("turn", F.col("conv_id") * 100_000 + F.col("turn"))
    vertices = t.select(F.col("conv_id").alias("graph_id"), at.alias("vid"), F.col("role").alias("vlabel"))
    after = t.select("conv_id", at.alias("src"), F.lead(at).over(Window.partitionBy("conv_id").orderBy("turn")).alias("dst")).where("dst is not null")
    return vertices, after.select(F.col("conv_id").alias("graph_id"), "src", "dst", F.lit(None).cast("string").alias("elabel"))


def order_graphs(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """O, a database of one graph for each order: the order, its parts and its suppliers, joined as in T."""
    g = trade(spark, sf_dir)
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    order, part, supplier, gid = vid("orders", "l_orderkey"), vid("part", "l_partkey"), vid("supplier", "l_suppkey"), F.col("l_orderkey").alias("graph_id")
    edges = li.select(gid, order.alias("src"), part.alias("dst"), F.lit("contains").alias("elabel")).union(li.select(gid, order, supplier, F.lit("sourced"))).union(li.select(gid, part, supplier, F.lit("supplies"))).distinct()
    members = edges.select("graph_id", F.col("src").alias("vid")).union(edges.select("graph_id", "dst")).distinct()
    return members.join(g.vertices, "vid").select("graph_id", "vid", "vlabel"), edges


def document_lines(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """L: documents that share a trimmed line, however many they are: each is joined to the least one that has the line.

    These stars connect what all pairs would, with one edge for a document and line, not one for each pair.
    """
    d = table(spark, sf_dir, "documents")
    members = document_line_members(spark, sf_dir)
    least = members.groupBy("line").agg(F.min("vid").alias("first"))
    vertices = d.select(vid("document", "doc_id").alias("vid"), F.concat("lang", F.lit("/"), "source").alias("vlabel"))
    return LabeledGraph(vertices, _edges(members.join(least, "line").where("vid <> first"), F.col("first"), F.col("vid"), None), simple=True)


def document_line_members(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vid, line): which document has which line (sha-256 of the trimmed line) that two or more documents have, however many."""
    d = table(spark, sf_dir, "documents")
    lines = d.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).where("line <> ''")
    lines = lines.select("doc_id", F.sha2("line", 256).alias("line")).distinct()
    used = lines.groupBy("line").agg(F.count("*").alias("n")).where("n > 1").select("line")
    return lines.join(used, "line").select(vid("document", "doc_id").alias("vid"), "line")


#: Vectors of a block that are compared at once.
VECTOR_BLOCK = 2048


def vector_neighbours(spark: SparkSession, sf_dir: str, least: float = 0.3) -> LabeledGraph:
    """K: embeddings whose cosine is over `least`, exactly: every block of vectors against every block, as matrix products.

    The work is quadratic, as the view is all pairs; a vector is sent once for each block, not once for each vector.
    """
    e = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    blocks = max(1, -(-e.count() // VECTOR_BLOCK))
    own = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    each = lambda from_, to, side: e.select("vec_id", "v", own.alias("b")).select("vec_id", "v", F.col("b"), F.explode(F.sequence(from_, to)).alias("o"), F.lit(side).alias("left"))
    left = each(F.col("b"), F.lit(blocks - 1), True).select(F.col("b").alias("i"), F.col("o").alias("j"), "left", "vec_id", "v")
    right = each(F.lit(0), F.col("b"), False).select(F.col("o").alias("i"), F.col("b").alias("j"), "left", "vec_id", "v")

    def over(group: pd.DataFrame) -> pd.DataFrame:
        sides = []
        for part in (group[group.left], group[~group.left]):
            m = np.stack(part.v.to_numpy()) if len(part) else np.empty((0, 1))
            norm = np.sqrt((m * m).sum(axis=1, keepdims=True))
            sides.append((part.vec_id.to_numpy(), np.divide(m, norm, out=np.zeros_like(m), where=norm > 0)))
        (ids, a), (others, b) = sides
        if not len(ids) or not len(others):
            return pd.DataFrame({"a": [], "b": []}, dtype="int64")
        x, y = np.nonzero(a @ b.T > least)
        x, y = ids[x], others[y]
        keep = x != y if group.i.iloc[0] != group.j.iloc[0] else x < y
        return pd.DataFrame({"a": np.minimum(x, y)[keep], "b": np.maximum(x, y)[keep]})

    pairs = left.union(right).groupBy("i", "j").applyInPandas(over, "a long, b long")
    return LabeledGraph(e.select(vid("vector", "vec_id").alias("vid"), F.concat(F.lit("V"), F.col("label").cast("string")).alias("vlabel")), _edges(pairs, vid("vector", "a"), vid("vector", "b"), None), simple=True)


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W: (page_id, host, target, n): how often a page links to a target."""
    p = table(spark, sf_dir, "pages")
    found = p.select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target"))
    return found.groupBy("page_id", "host", "target").agg(F.count("*").alias("n"))


def ring(spark: SparkSession, n: int, label: str = "A", reach: int = 1) -> LabeledGraph:
    """A regular graph with one label: each vertex joined to the `reach` that follow it around."""
    ids = spark.range(n)
    edges = ids.select(F.col("id"), F.explode(F.array(*(F.lit(k) for k in range(1, reach + 1)))).alias("k")).select("id", ((F.col("id") + F.col("k")) % n).alias("to"))
    return LabeledGraph(ids.select(F.col("id").alias("vid"), F.lit(label).alias("vlabel")), edges.select(F.least("id", "to").alias("src"), F.greatest("id", "to").alias("dst"), F.lit(None).cast("string").alias("elabel")).distinct())


GRAPHS = {"T": trade, "D": dense, "Y": few_labels, "H": many_labels, "E": event_succession}
