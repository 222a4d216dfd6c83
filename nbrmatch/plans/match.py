"""The whole method: label pruning and codes, peeling, candidates, search."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import filters, fixpoint, search
from ..operators.graph import LabeledGraph
from ..operators.pattern import Pattern, parse
from ..session import cut, discard


@dataclass
class Match:
    """engine: which search ran. written: the tables that embeddings read; discard(*written) when they are done with."""

    embeddings: DataFrame
    peeled: fixpoint.Peeled
    candidates: DataFrame
    sizes: dict[str, int]
    order: list[str]
    engine: str = "joins"

    @property
    def written(self) -> tuple[DataFrame, ...]:
        return self.peeled.state, self.peeled.adj, self.peeled.start.adj, self.candidates


def empty(spark: SparkSession, q: Pattern) -> DataFrame:
    return spark.createDataFrame([], ", ".join(f"m_{u} long" for u in sorted(q.vertices)))


def prepare(s: filters.Start, q: Pattern, test: filters.Test | None = None, max_rounds: int | None = None, how: str = "rarest_candidates") -> tuple[fixpoint.Peeled, DataFrame, dict[str, int], list[str]]:
    """Peeled graph, candidates (both written), their sizes and the order. test: None takes the code that fits q (filters.code_for)."""
    elabels = None
    if test is None:
        test, elabels = filters.code_for(q)
    p = fixpoint.peel(s, q, test, max_rounds, elabels=elabels)
    cand = cut(fixpoint.candidate_sets(p, q, test), "cand")
    sizes = fixpoint.candidate_sizes(cand, q)
    edges = search.edge_sizes(p.start, q) if how == "min_edge_card" else None
    return p, cand, sizes, search.order(q, sizes, edges, how=how)


def match(g: LabeledGraph, q: Pattern, *, access: str = "table", engine: str = "joins", how: str = "rarest_candidates", unique: str = "mapping", max_rounds: int | None = None, test: filters.Test | None = None, triples: bool = True) -> Match:
    """All embeddings of q in g.

    access: table reads the graph as it is; pass filters it first while edges are read once, grouped by source
    (streaming.edgepass). engine: joins or dfs. A pattern vertex without candidates ends the work before any search.
    Where all edges of q have labels, codes count edge labels too, by direction if q is directed.
    """
    spark = g.edges.sparkSession
    s = filters.start(g, q, triples)
    if access == "pass":
        from ..streaming import edgepass

        s = edgepass.prefilter(s, q)
    p, cand, sizes, sequence = prepare(s, q, test, max_rounds, how)
    if not all(sizes.values()):
        return Match(empty(spark, q), p, cand, sizes, sequence, "none")
    if engine == "dfs":
        ran = "dfs" if search.fits_dfs(p.adj, cand) else "joins"
        return Match(search.dfs(p.adj, cand, q, sequence), p, cand, sizes, sequence, ran)
    return Match(search.joins(p.adj, cand, q, sequence, unique, g.simple, sizes), p, cand, sizes, sequence)


def exists(g: LabeledGraph, q: Pattern) -> bool:
    return not match(g, q).embeddings.limit(1).isEmpty()


def count(g: LabeledGraph, q: Pattern) -> DataFrame:
    """(n): the number of embeddings; last leaves are counted, not listed, and parts that share no label multiply."""
    p, cand, sizes, _ = prepare(filters.start(g, q), q)
    if not all(sizes.values()):
        return g.edges.sparkSession.createDataFrame([(0,)], "n long")
    return search.count(p.adj, cand, q, g.simple)


def match_sql(spark: SparkSession, text: str, vertices: str = "g_vertices", edges: str = "g_edges", directed: bool = False) -> DataFrame:
    """Embeddings of a text pattern in the graph of two temporary views."""
    q = parse(text, directed or None)
    return match(LabeledGraph(spark.table(vertices), spark.table(edges), q.directed), q).embeddings


def register_views(g: LabeledGraph) -> None:
    g.vertices.createOrReplaceTempView("g_vertices")
    g.edges.createOrReplaceTempView("g_edges")
    g.adjacency().createOrReplaceTempView("g_adj")


def same_rows(a: DataFrame, b: DataFrame) -> DataFrame:
    """(only_a, only_b): both 0 if two results have the same rows as often."""
    one = a.exceptAll(b.select(*a.columns)).agg(F.count("*").alias("only_a"))
    return one.crossJoin(b.select(*a.columns).exceptAll(a).agg(F.count("*").alias("only_b")))


def run_set(g: LabeledGraph, patterns: dict[str, Pattern]) -> DataFrame:
    """(pattern_id, n_candidates, kept_vertices, rounds, n): many patterns over one graph whose label-pruned union is read once."""
    spark = g.edges.sparkSession
    labels = sorted({n for q in patterns.values() for n in q.labels})
    shared = g.induced(g.vertices.where(F.col("vlabel").isin(*labels)))
    shared = LabeledGraph(cut(shared.vertices, "set-v"), cut(shared.edges, "set-e"), g.directed, g.multi, g.simple)
    rows = []
    for name, q in patterns.items():
        m = match(shared, q)
        rows.append((name, sum(m.sizes.values()), m.peeled.state.count(), len(m.peeled.log), m.embeddings.count()))
        discard(*m.written)
    discard(shared.vertices, shared.edges)
    return spark.createDataFrame(rows, "pattern_id string, n_candidates long, kept_vertices long, rounds int, n long")
