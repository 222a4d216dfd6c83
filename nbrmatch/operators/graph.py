"""Labelled graphs as two DataFrames, and general operations on them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut


@dataclass
class LabeledGraph:
    """vertices: (vid long, vlabel string). edges: (src long, dst long, elabel string or null).

    Undirected edges are stored once, src < dst; directed ones as they are. Vertices without label match nothing.
    multi: edges may repeat. simple: no two edges join the same two vertices, whatever their labels.
    """

    vertices: DataFrame
    edges: DataFrame
    directed: bool = False
    multi: bool = False
    simple: bool = False

    def adjacency(self) -> DataFrame:
        """(src, dst, elabel, dir): every edge from both of its ends; dir 'B', or 'O' and 'I' as src sees a directed edge."""
        out, back = ("O", "I") if self.directed else ("B", "B")
        there = self.edges.select("src", "dst", "elabel", F.lit(out).alias("dir"))
        return there.union(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "elabel", F.lit(back).alias("dir")))

    def induced(self, keep: DataFrame) -> LabeledGraph:
        """The subgraph on the vertices whose vid is in keep (vid)."""
        vertices = self.vertices.join(keep.select("vid"), "vid", "left_semi")
        return LabeledGraph(vertices, both_ends(self.edges, keep), self.directed, self.multi, self.simple)


def both_ends(edges: DataFrame, keep: DataFrame) -> DataFrame:
    one = edges.join(keep.select(F.col("vid").alias("src")), "src", "left_semi")
    return one.join(keep.select(F.col("vid").alias("dst")), "dst", "left_semi").select(*edges.columns)


def build(vertices: DataFrame, edges: DataFrame, directed: bool = False, multi: bool = False) -> LabeledGraph:
    """A graph from raw rows: self-loops and edges without an end are dropped, repeated edges collapse unless multi.

    Of a repeated vertex the least label stays; a null label too (it matches nothing). dropped() counts what went.
    """
    vertices = vertices.where("vid is not null").groupBy("vid").agg(F.min("vlabel").alias("vlabel"))
    found = edges.where("src is not null and dst is not null and src <> dst").select("src", "dst", "elabel")
    if not directed:
        found = found.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "elabel")
    return LabeledGraph(vertices, found if multi else found.distinct(), directed, multi)


def dropped(edges: DataFrame) -> DataFrame:
    """(self_loops, no_end, repeated) of raw edges."""
    loops = F.sum(F.when(F.col("src") == F.col("dst"), 1).otherwise(0))
    none = F.sum(F.when(F.col("src").isNull() | F.col("dst").isNull(), 1).otherwise(0))
    good = edges.where("src <> dst")
    once = good.select(F.least("src", "dst"), F.greatest("src", "dst"), "elabel").distinct().agg(F.count("*").alias("once"))
    return edges.agg(loops.alias("self_loops"), none.alias("no_end"), F.count(F.when(F.col("src") != F.col("dst"), 1)).alias("good")).crossJoin(once).select("self_loops", "no_end", (F.col("good") - F.col("once")).alias("repeated"))


def degrees(g: LabeledGraph) -> DataFrame:
    """(vid, deg) of every vertex, also those without edges."""
    counted = g.adjacency().groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"))
    return g.vertices.select("vid").join(counted, "vid", "left").select("vid", F.coalesce("deg", F.lit(0)).cast("long").alias("deg"))


def summary(g: LabeledGraph) -> DataFrame:
    """One row: vertices with edges, edges, labels among them, mean and largest degree, density."""
    deg = g.adjacency().groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"))
    n, m = F.count("*"), F.sum("deg") / 2
    return deg.join(g.vertices, "vid").agg(
        n.alias("n_vertices"), m.cast("long").alias("n_edges"), F.countDistinct("vlabel").alias("n_labels"),
        F.round(F.avg("deg"), 6).alias("avg_degree"), F.max("deg").alias("max_degree"), F.round(2 * m / (n * (n - 1)), 9).alias("density"),
    )


def label_histogram(g: LabeledGraph) -> DataFrame:
    return g.vertices.groupBy("vlabel").agg(F.count("*").alias("n"))


def k_core(g: LabeledGraph, k: int) -> DataFrame:
    """(vid) of the largest set in which every vertex has k neighbours of the set, by rounds of removal."""
    edges, alive = cut(g.adjacency().select("src", "dst").distinct(), "core-edges"), None
    before = -1
    while True:
        alive = edges.groupBy("src").agg(F.count("*").alias("n")).where(F.col("n") >= k).select(F.col("src").alias("vid"))
        edges = cut(both_ends(edges, alive), "core-edges")
        left = edges.count()
        if left == before:
            return edges.select(F.col("src").alias("vid")).distinct()
        before = left


def connected_components(g: LabeledGraph, rounds: int = 60) -> DataFrame:
    """(vid, component): the least vid reached. Labels spread over edges and jump to their label's label each round."""
    adj = cut(g.adjacency().select("src", "dst").distinct(), "cc-edges")
    state = cut(g.vertices.select("vid", F.col("vid").alias("component")), "cc")
    for _ in range(rounds):
        near = adj.join(state, adj["dst"] == state["vid"]).groupBy("src").agg(F.min("component").alias("near"))
        spread = state.join(near, state["vid"] == near["src"], "left").select("vid", F.col("component").alias("old"), F.least("component", F.coalesce("near", "component")).alias("component"))
        target = spread.select(F.col("vid").alias("component"), F.col("component").alias("jump"))
        new = cut(spread.join(target, "component", "left").select("vid", "old", F.least("component", F.coalesce("jump", "component")).alias("component")), "cc")
        changed = not new.where("old <> component").isEmpty()
        state = new.select("vid", "component")
        if not changed:
            return state
    raise RuntimeError("components didn't settle")


def bfs_levels(g: LabeledGraph, start: DataFrame, most: int = 50) -> DataFrame:
    """(vid, level) of the vertices within `most` hops of start (vid)."""
    adj = g.adjacency().select("src", "dst").distinct()
    seen = cut(start.select("vid", F.lit(0).alias("level")).distinct(), "bfs")
    front = seen
    for level in range(1, most + 1):
        reached = adj.join(front.select(F.col("vid").alias("src")), "src", "left_semi").select(F.col("dst").alias("vid")).distinct()
        front = cut(reached.join(seen, "vid", "left_anti").withColumn("level", F.lit(level)), "bfs")
        if front.isEmpty():
            break
        seen = seen.union(front)
    return seen
