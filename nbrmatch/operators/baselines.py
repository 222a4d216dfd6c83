"""Matchers to compare with: no filter, single filters, candidate refinement, and the tree-index matcher."""

from __future__ import annotations

import time
from concurrent.futures import FIRST_COMPLETED, ThreadPoolExecutor, wait
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from . import filters, search
from .graph import LabeledGraph
from .pattern import Pattern


def one_shot(g: LabeledGraph, q: Pattern, test: filters.Test, need_mnd: bool = False) -> tuple[filters.Start, DataFrame]:
    """(label-pruned graph, candidates) by one filter, applied once. Adjacency and candidates are written, as each pattern edge reads them."""
    s = filters.start(g, q)
    s = filters.Start(s.vertices, cut(s.adj, "adj"), s.ranks, s.directed, s.simple)
    features = filters.one_hop(s)
    if need_mnd:
        features = filters.with_mnd(cut(features, "features"), s)
    return s, cut(filters.candidates(features, q, test), "cand")


def brute(g: LabeledGraph, q: Pattern) -> DataFrame:
    """Labels and edges alone."""
    s, cand = one_shot(g, q, filters.label)
    return search.joins(s.adj, cand, q, search.order(q, how="bfs"), simple=s.simple)


def degree_only(g: LabeledGraph, q: Pattern) -> DataFrame:
    s, cand = one_shot(g, q, filters.degree)
    return search.joins(s.adj, cand, q, simple=s.simple)


def nlf(g: LabeledGraph, q: Pattern) -> DataFrame:
    s, cand = one_shot(g, q, filters.nlf)
    return search.joins(s.adj, cand, q, simple=s.simple)


def mnd_nlf(g: LabeledGraph, q: Pattern) -> DataFrame:
    s, cand = one_shot(g, q, filters.mnd_nlf, need_mnd=True)
    return search.joins(s.adj, cand, q, simple=s.simple)


def refine(g: LabeledGraph, q: Pattern, levels: int | None = None) -> DataFrame:
    """(u, vid) by label and degree, then each candidate must keep a candidate neighbour for each pattern neighbour.

    Rounds until nothing changes, or `levels` of them.
    """
    s, cand = one_shot(g, q, filters.degree)
    before, n = -1, 0
    while levels is None or n < levels:
        size = cand.count()
        if size == before:
            break
        before, n = size, n + 1
        kept = None
        for u in sorted(q.vertices):
            own = cand.where(F.col("u") == u)
            for w in sorted(set(q.neighbours(u))):
                own = own.join(search.edge_table(s.adj, cand, q, w, u, s.simple).select(F.col(f"m_{u}").alias("vid")), "vid", "left_semi")
            own = own.select("u", "vid")
            kept = own if kept is None else kept.union(own)
        cand = cut(kept, "refine")
    return cand


def refined(g: LabeledGraph, q: Pattern) -> DataFrame:
    return search.joins(cut(filters.start(g, q).adj, "adj"), refine(g, q), q, simple=g.simple)


@dataclass
class TreeIndex:
    """One table (m_parent, m_child) for each edge of a breadth-first tree of the pattern, and the reduced candidates."""

    tables: dict[tuple[str, str], DataFrame]
    cand: DataFrame
    order: list[str]
    adj: DataFrame
    simple: bool = False

    def rows(self) -> DataFrame:
        """(parent, child, n): what the index stores."""
        out = None
        for (a, b), t in self.tables.items():
            one = t.agg(F.count("*").alias("n")).select(F.lit(a).alias("parent"), F.lit(b).alias("child"), "n")
            out = one if out is None else out.union(one)
        return out


def tree_index(g: LabeledGraph, q: Pattern) -> TreeIndex:
    """Build the index: filtered candidates, tree edges reduced top-down then bottom-up, stored."""
    if not q.connected or len(q.vertices) < 2:
        raise ValueError("the tree index takes connected patterns with an edge")
    s, cand = one_shot(g, q, filters.mnd_nlf, need_mnd=True)
    adj = s.adj
    core = q.core()
    root = min(core, key=lambda u: (-q.pdeg(u), u))
    parent: dict[str, str] = {}
    line = [root]
    for u in line:
        for w in sorted(q.neighbours(u), key=lambda w: (w not in core, -q.pdeg(w), w)):
            if w not in parent and w != root:
                parent[w] = u
                line.append(w)
    of = {u: cand.where(F.col("u") == u).select("vid") for u in q.vertices}
    tables: dict[tuple[str, str], DataFrame] = {}
    for u in line[1:]:  # top-down: a child needs a parent that is left
        w = parent[u]
        found = search.edge_table(adj, cand, q, w, u, s.simple).join(of[w].select(F.col("vid").alias(f"m_{w}")), f"m_{w}", "left_semi")
        tables[w, u] = cut(found, "index")
        of[u] = tables[w, u].select(F.col(f"m_{u}").alias("vid")).distinct()
    for u in reversed(line[1:]):  # bottom-up: a parent needs a child that is left
        w = parent[u]
        children = of[u].select(F.col("vid").alias(f"m_{u}"))
        tables[w, u] = cut(tables[w, u].join(children, f"m_{u}", "left_semi"), "index")
        of[w] = of[w].join(tables[w, u].select(F.col(f"m_{w}").alias("vid")), "vid", "left_semi")
    for u in line[1:]:  # and once more down, so that the tables agree
        w = parent[u]
        tables[w, u] = cut(tables[w, u].join(of[w].select(F.col("vid").alias(f"m_{w}")), f"m_{w}", "left_semi"), "index")
        of[u] = tables[w, u].select(F.col(f"m_{u}").alias("vid")).distinct()
    left = None
    for u in sorted(q.vertices):
        one = of[u].select(F.lit(u).alias("u"), "vid")
        left = one if left is None else left.union(one)
    leaf = lambda u: q.pdeg(u) == 1
    rank = {u: (u not in core, leaf(u), line.index(u)) for u in line}
    order: list[str] = []
    while len(order) < len(line):
        order.append(min((u for u in line if u not in order and (u == root or parent[u] in order)), key=rank.get))
    return TreeIndex(tables, cut(left, "index-cand"), order, adj, s.simple)


def tree_index_match(index: TreeIndex, q: Pattern) -> DataFrame:
    """Embeddings over the index: core first, then the forest, leaves last; edges outside the tree are checked as joins."""
    rows, placed = None, []
    for u in index.order:
        tree = next(((p, c) for p, c in index.tables if c == u), None)
        if tree is None:
            rows = index.cand.where(F.col("u") == u).select(F.col("vid").alias(f"m_{u}"))
        else:
            rows = rows.join(index.tables[tree], f"m_{tree[0]}")
            for w in sorted({w for w in q.neighbours(u) if w in placed and w != tree[0]}):
                rows = rows.join(search.edge_table(index.adj, index.cand, q, w, u, index.simple), [f"m_{w}", f"m_{u}"], "left_semi")
        for w in placed:
            if q.vertices[w] == q.vertices[u]:
                rows = rows.where(F.col(f"m_{w}") != F.col(f"m_{u}"))
        placed.append(u)
    return rows.select(*(f"m_{u}" for u in sorted(q.vertices)))


def race(spark, runs: dict[str, callable], deadline_s: float = 3600.0) -> tuple[str, object, float]:
    """Run several matchers (callables with an action inside) at once; the first result wins, the others are cancelled."""
    began = time.monotonic()

    def one(name: str):
        spark.sparkContext.setJobGroup(f"race-{name}", name, interruptOnCancel=True)
        return name, runs[name]()

    pool = ThreadPoolExecutor(len(runs))
    try:
        futures = [pool.submit(one, n) for n in runs]
        done, rest = wait(futures, timeout=deadline_s, return_when=FIRST_COMPLETED)
        if not done:
            raise TimeoutError("no matcher finished")
        name, result = next(iter(done)).result()
        return name, result, time.monotonic() - began
    finally:
        for n in runs:
            spark.sparkContext.cancelJobGroup(f"race-{n}")
        pool.shutdown(wait=False, cancel_futures=True)
