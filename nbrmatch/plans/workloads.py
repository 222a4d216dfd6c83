"""Experiment workloads: patterns from random walks, sets of patterns timed by method, and special graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, filters, fixpoint
from ..operators.graph import LabeledGraph
from ..operators.pattern import Pattern
from ..session import SMALL_ROWS, cut, discard
from . import measures
from .match import match


def walk(g: LabeledGraph, size: int, kind: str = "sparse", n: int = 5, seed: int = 42, induced: bool = True) -> list[Pattern]:
    """n connected patterns of `size` vertices by walks to the neighbour with the least (sparse) or most (dense) neighbours.

    Only unvisited neighbours count; a walk that is stuck goes on from any visited vertex. Ties go by a seeded hash. All
    walks advance together: a step is a join of their heads with the adjacency and one aggregation, and brings one row a
    walk to the driver, however many neighbours the heads have. induced: all edges between visited vertices, else those
    of the walk.
    """
    if kind not in ("sparse", "dense"):
        raise ValueError(kind)
    spark = g.edges.sparkSession
    adj = g.adjacency().select("src", "dst").distinct()
    deg = cut(adj.groupBy(F.col("src").alias("dst")).agg(F.count("*").alias("deg")), "walk-deg")
    near = cut(adj.join(deg, "dst").select("src", "dst", "deg"), "walk-near")
    starts = [r["dst"] for r in deg.orderBy(F.xxhash64(F.lit(seed), "dst"), "dst").limit(n).collect()]
    walks: list[list[int]] = [[s] for s in starts]
    steps: list[list[tuple[int, int]]] = [[] for _ in starts]
    sign = 1 if kind == "sparse" else -1

    def advance(k: int, heads: list[tuple[int, int]]) -> dict[int, tuple[int, int]]:
        """For each walk with an unvisited neighbour of its heads: (head, neighbour)."""
        at = F.broadcast(spark.createDataFrame(heads, "walk int, src long"))
        seen = F.broadcast(spark.createDataFrame([(i, v) for i, w in enumerate(walks) for v in w], "walk int, dst long"))
        free = near.join(at, "src").join(seen, ["walk", "dst"], "left_anti")
        best = F.min(F.struct(F.col("deg") * sign, F.xxhash64(F.lit(seed), "walk", F.lit(k), "dst"), "dst", "src")).alias("s")
        return {r["walk"]: (r["s"]["src"], r["s"]["dst"]) for r in free.groupBy("walk").agg(best).collect()}

    for k in range(1, size):
        found = advance(k, [(i, w[-1]) for i, w in enumerate(walks)])
        if stuck := [(i, v) for i, w in enumerate(walks) if i not in found for v in w]:
            found |= advance(k, stuck)
        for i, (x, v) in found.items():
            walks[i].append(v)
            steps[i].append((x, v))
    ids = sorted({v for w in walks for v in w})
    some = F.broadcast(spark.createDataFrame([(v,) for v in ids], "vid long"))
    labels = {r["vid"]: r["vlabel"] for r in g.vertices.join(some, "vid").collect()}
    inner = g.edges.join(some.withColumnRenamed("vid", "src"), "src").join(some.withColumnRenamed("vid", "dst"), "dst")
    edges = sorted((r["src"], r["dst"]) for r in inner.select("src", "dst").distinct().collect())  # between the walks' vertices
    discard(deg, near)
    out = []
    for w, s in zip(walks, steps, strict=True):
        name = {v: f"u{k}" for k, v in enumerate(w)}
        walked = {frozenset(x) for x in s}
        own = [(name[a], name[b], None) for a, b in edges if a in name and b in name and (induced or frozenset((a, b)) in walked)]
        out.append(Pattern({name[v]: labels[v] for v in w}, tuple(own), g.directed))
    return out


def as_text(q: Pattern) -> str:
    """The pattern in the form that parse() reads."""
    part = lambda u: f"({u}:{q.vertices[u]})"
    arrow = "->" if q.directed else "-"
    alone = [part(u) for u in q.vertices if not q.neighbours(u)]
    return ", ".join([*(f"{part(a)}-{f'[{e}]-' if e else ''}{arrow[1:]}{part(b)}" for a, b, e in q.edges), *alone])


ENGINES = ("codes", "nlf", "mnd_nlf", "degree_only", "tree_index")


def run_one(g: LabeledGraph, q: Pattern, engine: str) -> tuple[DataFrame, list[DataFrame], list[DataFrame]]:
    """(embeddings, tables written for them, tables of an index): by one engine."""
    if engine == "codes":
        found = match(g, q)
        return found.embeddings, list(found.written[:2]) + [found.candidates], []
    if engine == "tree_index" and len(q.vertices) > 1:
        index = baselines.tree_index(g, q)
        return baselines.tree_index_match(index, q), [index.adj, index.cand], list(index.tables.values())
    return getattr(baselines, "brute" if engine == "tree_index" else engine)(g, q), [], []


def sets(spark: SparkSession, graphs: dict[str, LabeledGraph], sizes: list[int], kinds: tuple[str, ...] = ("sparse", "dense"), engines: tuple[str, ...] = ("codes", "tree_index"), n: int = 5, deadline_s: float = 60.0) -> DataFrame:
    """One row for each graph, kind, size and engine: mean and median seconds, or INF beyond the set's deadline, embeddings and stored bytes.

    bytes: what the engine has written for a pattern and keeps for the search, on average (measures.stored_bytes): peeled
    state, adjacency and candidates for codes; adjacency, candidates and tree tables for the index.
    """
    rows = []
    for name, g in graphs.items():
        g = LabeledGraph(cut(g.vertices, "set-v"), cut(g.edges, "set-e"), g.directed, g.multi, g.simple)
        for kind in kinds:
            for size in sizes:
                patterns = walk(g, size, kind, n)
                for engine in engines:
                    found: list[int] = []
                    stored: list[int] = []

                    def run(q: Pattern, engine: str = engine, found: list = found, stored: list = stored, g: LabeledGraph = g) -> None:
                        result, kept, index = run_one(g, q, engine)
                        found.append(result.count())
                        stored.append(measures.stored_bytes(kept) + measures.stored_bytes(index))
                        discard(*kept, *index)

                    t = measures.timed([lambda q=q, run=run: run(q) for q in patterns], spark, deadline_s)
                    rows.append((name, kind, size, engine, len(patterns), t["status"], t.get("mean_s"), t.get("median_s"), sum(found), sum(stored) // max(1, len(stored))))
    return spark.createDataFrame(rows, "graph string, kind string, size int, engine string, patterns int, status string, mean_s double, median_s double, embeddings long, bytes long")


def fixed_set(g: LabeledGraph, patterns: dict[str, Pattern]) -> DataFrame:
    """(pattern, codes, nlf, tree_index): embeddings of each pattern by three engines; they must agree."""
    spark = g.edges.sparkSession
    g = LabeledGraph(cut(g.vertices, "set-v"), cut(g.edges, "set-e"), g.directed, g.multi, g.simple)
    rows = []
    for name, q in patterns.items():
        counts = []
        for engine in ("codes", "nlf", "tree_index"):
            result, kept, index = run_one(g, q, engine)
            counts.append(result.count())
            discard(*kept, *index)
        rows.append((name, *counts))
    discard(g.vertices, g.edges)
    return spark.createDataFrame(rows, "pattern string, codes long, nlf long, tree_index long")


def speed_up(results: DataFrame, base: str = "tree_index") -> DataFrame:
    """(graph, kind, ratio, bytes_ratio, sizes): of mean seconds and of stored bytes, mean over the sizes where both finished."""
    own = results.where("engine = 'codes' and status = 'ok'").select("graph", "kind", "size", F.col("mean_s").alias("own"), F.col("bytes").alias("own_bytes"))
    other = results.where((F.col("engine") == base) & (F.col("status") == "ok")).select("graph", "kind", "size", F.col("mean_s").alias("other"), F.col("bytes").alias("other_bytes"))
    means = F.avg(F.col("other") / F.col("own")).alias("ratio"), F.avg(F.col("other_bytes") / F.col("own_bytes")).alias("bytes_ratio"), F.count("*").alias("sizes")
    return own.join(other, ["graph", "kind", "size"]).groupBy("graph", "kind").agg(*means)


def pruning(g: LabeledGraph, patterns: list[Pattern]) -> DataFrame:
    """(filter, pairs, vertices) summed over patterns, one-shot, and what peeling leaves (peel)."""
    spark, total, kept, pairs = g.edges.sparkSession, None, 0, 0
    for q in patterns:
        s = filters.start(g, q)
        s = filters.Start(s.vertices, cut(s.adj, "adj"), s.ranks, s.directed, s.simple)
        one = measures.pairs_per_filter(filters.with_mnd(filters.one_hop(s), s), q)
        total = one if total is None else total.union(one)
        p = fixpoint.peel(s, q)
        kept, pairs = kept + p.state.count(), pairs + fixpoint.candidate_sets(p, q).count()
    summed = total.groupBy("filter").agg(F.sum("pairs").alias("pairs"), F.sum("vertices").alias("vertices"))
    return summed.union(spark.createDataFrame([("peel", pairs, kept)], "filter string, pairs long, vertices long"))


def small_enough(df: DataFrame, most: int = SMALL_ROWS) -> bool:
    return df.limit(most + 1).count() <= most
