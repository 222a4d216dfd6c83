"""Enumerating embeddings: joins along the pattern's edges, or depth-first search in one pass over start candidates."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import SMALL_ROWS
from .filters import Start
from .pattern import Pattern

ORDERS = ("given", "bfs", "rarest_candidates", "min_edge_card", "degree_desc", "core_first")


def order(q: Pattern, sizes: dict[str, int] | None = None, edge_sizes: dict[tuple[str, str], int] | None = None, how: str = "rarest_candidates") -> list[str]:
    """The pattern's vertices, each next to an earlier one where the pattern is connected."""
    sizes, names = sizes or {}, list(q.vertices)
    core = set(q.core())
    edge = lambda a, b: (edge_sizes or {}).get((a, b), (edge_sizes or {}).get((b, a), 0))
    if how == "given":
        key = lambda u, done: (names.index(u),)
    elif how == "bfs":
        key = lambda u, done: (min((done.index(w) for w in q.neighbours(u) if w in done), default=0), names.index(u))
    elif how == "degree_desc":
        key = lambda u, done: (-q.pdeg(u), u)
    elif how == "min_edge_card":
        key = lambda u, done: (min((edge(w, u) for w in q.neighbours(u) if w in done or not done), default=0), u)
    elif how == "core_first":
        key = lambda u, done: (u not in core, q.pdeg(u) == 1, sizes.get(u, 0), u)
    elif how == "rarest_candidates":
        key = lambda u, done: (-sum(w in done for w in q.neighbours(u)), sizes.get(u, 0), u)
    else:
        raise ValueError(how)
    out: list[str] = []
    while len(out) < len(names):
        rest = [u for u in names if u not in out]
        near = [u for u in rest if how == "given" or not out or any(w in out for w in q.neighbours(u))] or rest
        out.append(min(near, key=lambda u: key(u, out)))
    return out


def edge_sizes(s: Start, q: Pattern) -> dict[tuple[str, str], int]:
    """How many edges of the label-pruned graph fit each pattern edge, by the labels of both ends and of the edge. One aggregation."""
    ends = s.vertices.select(F.col("vid").alias("src"), F.col("rank").alias("src_rank"))
    some = s.adj.where(F.col("dir") != "I").join(ends, "src").groupBy("src_rank", "rank", "elabel").agg(F.count("*").alias("n"))
    found: dict[tuple[int, int, str | None], int] = {}
    for r in some.collect():  # as many rows as there are triples of pattern labels and edge labels
        for e in (None, r["elabel"]) if r["elabel"] is not None else (None,):
            key = (r["src_rank"], r["rank"], e)
            found[key] = found.get(key, 0) + r["n"]
    rank = lambda u: s.ranks[q.vertices[u]]
    return {(a, b): found.get((rank(a), rank(b), e), 0) for a, b, e in q.edges}


def edge_table(adj: DataFrame, cand: DataFrame, q: Pattern, w: str, u: str, simple: bool = False, sizes: dict[str, int] | None = None) -> DataFrame:
    """(m_w, m_u): the edges between candidates of w and of u that satisfy every pattern edge between them.

    simple: the graph has no parallel edges, so rows are distinct as they are. sizes: candidates of each pattern vertex;
    small sets are broadcast.
    """
    out = None
    for a, b, e in q.edges:
        if {a, b} != {w, u}:
            continue
        way = F.lit(True) if not q.directed else F.col("dir") == ("O" if a == w else "I")
        found = adj.where(way if e is None else way & (F.col("elabel") == e)).select(F.col("src").alias(f"m_{w}"), F.col("dst").alias(f"m_{u}"))
        found = found if simple else found.distinct()
        out = found if out is None else out.join(found, [f"m_{w}", f"m_{u}"], "left_semi")
    return out.join(_of(cand, w, sizes), f"m_{w}", "left_semi").join(_of(cand, u, sizes), f"m_{u}", "left_semi")


def _of(cand: DataFrame, u: str, sizes: dict[str, int] | None) -> DataFrame:
    own = cand.where(F.col("u") == u).select(F.col("vid").alias(f"m_{u}"))
    return F.broadcast(own) if sizes and sizes.get(u, SMALL_ROWS + 1) <= SMALL_ROWS else own


def joins(adj: DataFrame, cand: DataFrame, q: Pattern, sequence: list[str] | None = None, unique: str = "mapping", simple: bool = False, sizes: dict[str, int] | None = None) -> DataFrame:
    """One row m_<u> for each embedding: injective, keeps labels and edges, need not be induced.

    Left-deep joins; edges back to matched vertices are further keys of the same join, and inequality is asked only
    between vertices of one label. unique='subgraph' keeps one of the mappings that differ by an automorphism. adj and
    cand should be written tables, as each pattern edge reads them. Parts of a disconnected pattern are combined by a
    product, as its answer is one; count() multiplies instead.
    """
    sequence = sequence or order(q)
    placed: list[str] = []
    rows: DataFrame | None = None
    for u in sequence:
        own = cand.where(F.col("u") == u).select(F.col("vid").alias(f"m_{u}"))
        near = sorted({w for w in q.neighbours(u) if w in placed}, key=placed.index)
        if rows is None:
            rows = own
        elif not near:
            rows = rows.crossJoin(own)
        else:
            for k, w in enumerate(near):
                found = edge_table(adj, cand, q, w, u, simple, sizes)
                if k == 0:  # the first edge table has the candidates of both ends already
                    rows = found if len(placed) == 1 else rows.join(found, f"m_{w}")
                else:
                    rows = rows.join(found, [f"m_{w}", f"m_{u}"], "left_semi")
        for w in placed:
            if q.vertices[w] == q.vertices[u]:
                rows = rows.where(F.col(f"m_{w}") != F.col(f"m_{u}"))
        placed.append(u)
    names = [f"m_{u}" for u in sorted(q.vertices)]
    rows = rows.select(*names)
    if unique == "subgraph":
        own = F.array(*names)
        for m in q.automorphisms():
            rows = rows.where(own <= F.array(*(f"m_{m[u]}" for u in sorted(q.vertices))))
    return rows


def as_arrays(rows: DataFrame) -> DataFrame:
    return rows.select(F.array(*sorted(rows.columns)).alias("embedding"))


def as_maps(rows: DataFrame) -> DataFrame:
    return rows.select(F.create_map(*(x for c in sorted(rows.columns) for x in (F.lit(c[2:]), F.col(c)))).alias("embedding"))


def parts(q: Pattern) -> list[Pattern]:
    """The connected parts of a pattern."""
    out, left = [], set(q.vertices)
    while left:
        own = q.hops(min(left)).keys()
        out.append(Pattern({u: n for u, n in q.vertices.items() if u in own}, tuple(e for e in q.edges if e[0] in own), q.directed))
        left -= own
    return out


def count(adj: DataFrame, cand: DataFrame, q: Pattern, simple: bool = False) -> DataFrame:
    """(n) embeddings, without listing the last leaves: leaves of one parent multiply, if no other vertex has their label.

    Parts of a disconnected pattern that share no label are counted by themselves and multiplied.
    """
    own = parts(q)
    if len(own) > 1 and sum(len(set(p.labels)) for p in own) == len(q.labels):
        n, product = None, F.lit(1).cast("long")
        for k, p in enumerate(own):
            one = count(adj, cand, p, simple).select(F.col("n").alias(f"n_{k}"))
            n = one if n is None else n.crossJoin(one)  # one row each
            product = product * F.col(f"n_{k}")
        return n.select(product.alias("n"))
    labels = list(q.vertices.values())
    leaves = [u for u in sorted(q.vertices) if q.pdeg(u) == 1 and labels.count(q.vertices[u]) == 1 and q.pdeg(q.neighbours(u)[0]) > 1]
    if len(q.vertices) - len(leaves) < 1 or not leaves:
        return joins(adj, cand, q, simple=simple).agg(F.count("*").alias("n"))
    inner = Pattern({u: n for u, n in q.vertices.items() if u not in leaves}, tuple(e for e in q.edges if e[0] not in leaves and e[1] not in leaves), q.directed)
    rows, product = joins(adj, cand, inner, simple=simple), F.lit(1).cast("long")
    for u in leaves:
        w = q.neighbours(u)[0]
        rows = rows.join(edge_table(adj, cand, q, w, u, simple).groupBy(f"m_{w}").agg(F.count("*").alias(f"n_{u}")), f"m_{w}")
        product = product * F.col(f"n_{u}")
    return rows.agg(F.coalesce(F.sum(product), F.lit(0)).alias("n"))


def merged_equivalents(q: Pattern) -> list[list[str]]:
    """Groups of pattern vertices of one label with the same neighbours and no edge between them: they swap freely."""
    groups: dict[tuple, list[str]] = {}
    for u in sorted(q.vertices):
        way = sorted((w if u == a else a, e, u == a) for a, w, e in q.edges if u in (a, w))
        groups.setdefault((q.vertices[u], str(way)), []).append(u)
    return [g for g in groups.values() if len(g) > 1]


def joins_merged(adj: DataFrame, cand: DataFrame, q: Pattern, simple: bool = False) -> DataFrame:
    """joins() where swappable vertices are matched once in increasing order, then expanded to all their orders."""
    from itertools import permutations

    groups = merged_equivalents(q)
    rows = joins(adj, cand, q, simple=simple)
    for g in groups:
        for a, b in zip(g, g[1:], strict=False):
            rows = rows.where(F.col(f"m_{a}") < F.col(f"m_{b}"))
    for g in groups:
        orders = F.explode(F.array(*(F.struct(*(F.col(f"m_{a}").alias(f"m_{b}") for a, b in zip(p, g, strict=True))) for p in permutations(g))))
        rows = rows.withColumn("_g", orders).select(*(c for c in rows.columns if c[2:] not in g), *(F.col(f"_g.m_{u}").alias(f"m_{u}") for u in g))
    return rows.select(*(f"m_{u}" for u in sorted(q.vertices)))


def fits_dfs(adj: DataFrame, cand: DataFrame, most_rows: int = SMALL_ROWS) -> bool:
    """Whether dfs() searches depth-first, or leaves the work to joins()."""
    return adj.limit(most_rows + 1).count() <= most_rows and cand.limit(most_rows + 1).count() <= most_rows


def dfs(adj: DataFrame, cand: DataFrame, q: Pattern, sequence: list[str] | None = None, lookahead: bool = False, most_rows: int = SMALL_ROWS) -> DataFrame:
    """Depth-first search over a broadcast copy of the filtered graph, one task for a share of the first vertex's candidates.

    For filtered graphs of at most `most_rows` adjacency rows and candidates: their sizes are checked first, and larger
    ones go to joins(), see fits_dfs(). lookahead: a vertex is tried only if it has as many unused neighbours as its pattern vertex
    has unmatched ones.
    """
    sequence = sequence or order(q)
    if not fits_dfs(adj, cand, most_rows):
        return joins(adj, cand, q, sequence)
    spark = adj.sparkSession
    sets: dict[str, set[int]] = {u: set() for u in q.vertices}
    for r in cand.collect():
        sets[r["u"]].add(r["vid"])
    near: dict[int, dict[int, list[tuple]]] = {}
    for r in adj.collect():
        near.setdefault(r["src"], {}).setdefault(r["dst"], []).append((r["dir"], r["elabel"]))
    shared = spark.sparkContext.broadcast((sets, near))
    directed, edges, names = q.directed, q.edges, [f"m_{u}" for u in sorted(q.vertices)]
    touching = {u: [e for e in edges if u in e[:2]] for u in q.vertices}

    def fits(u: str, v: int, m: dict[str, int], graph: dict) -> bool:
        for a, b, e in touching[u]:
            w = b if a == u else a
            if w in m:
                want = ("O" if a == u else "I") if directed else None
                if not any((want is None or d == want) and (e is None or x == e) for d, x in graph.get(v, {}).get(m[w], ())):
                    return False
        if lookahead:
            open_ = len({(e[1] if e[0] == u else e[0]) for e in touching[u]} - m.keys())
            if len(graph.get(v, {}).keys() - set(m.values())) < open_:
                return False
        return True

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sets, graph = shared.value

        def search(m: dict[str, int]) -> Iterator[dict[str, int]]:
            if len(m) == len(sequence):
                yield dict(m)
                return
            u = sequence[len(m)]
            back = [e[1] if e[0] == u else e[0] for e in touching[u]]
            pool = sets[u]
            for w in back:
                if w in m:
                    pool = pool & graph.get(m[w], {}).keys()
            for v in sorted(pool - set(m.values())):
                if fits(u, v, m, graph):
                    m[u] = v
                    yield from search(m)
                    del m[u]

        for batch in batches:
            block = []
            for v in batch["vid"]:
                for m in search({sequence[0]: int(v)}):
                    block.append([m[n[2:]] for n in names])
                    if len(block) >= 10_000:
                        yield pd.DataFrame(block, columns=names)
                        block = []
            yield pd.DataFrame(block, columns=names, dtype="int64")

    first = cand.where(F.col("u") == sequence[0]).select("vid")
    return first.repartition("vid").mapInPandas(run, ", ".join(f"{n} long" for n in names))
