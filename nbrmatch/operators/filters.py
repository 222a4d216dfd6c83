"""Neighbourhood features of vertices and the filters that compare them with a pattern's.

The pattern is known when the plan is made, so its vectors and codes become literals of one expression: no join with a
pattern table, and each (vertex, pattern vertex) test runs in generated code, cheapest condition first.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import codes
from .graph import LabeledGraph, both_ends
from .pattern import Pattern


def rank_column(label: Column, ranks: dict[str, int]) -> Column:
    out = F.lit(0)
    for name, rank in ranks.items():
        out = F.when(label == name, rank).otherwise(out)
    return out


@dataclass
class Start:
    """The label-pruned graph: vertices (vid, vlabel, rank); adj (src, dst, elabel, dir, rank of dst). simple: as LabeledGraph."""

    vertices: DataFrame
    adj: DataFrame
    ranks: dict[str, int]
    directed: bool
    simple: bool = False


def start(g: LabeledGraph, q: Pattern, triples: bool = True, ranks: dict[str, int] | None = None) -> Start:
    """Keep vertices with a pattern label and edges between them; with triples also only edges whose labels occur in q.

    An edge label of None in q matches any edge.
    """
    ranks = ranks or q.ranks()
    vertices = g.vertices.where(F.col("vlabel").isin(*ranks)).select("vid", "vlabel", rank_column(F.col("vlabel"), ranks).alias("rank"))
    ends = vertices.select("vid", F.col("rank"))
    adj = g.adjacency().join(ends.select(F.col("vid").alias("src"), F.col("rank").alias("src_rank")), "src").join(ends.select(F.col("vid").alias("dst"), F.col("rank").alias("dst_rank")), "dst")
    if triples:
        some = F.lit(False)
        for a, b, e in sorted(q.triples(), key=str):
            same = (F.col("src_rank") == ranks[a]) & (F.col("dst_rank") == ranks[b])
            if q.directed:
                same = (same & (F.col("dir") == "O")) | ((F.col("src_rank") == ranks[b]) & (F.col("dst_rank") == ranks[a]) & (F.col("dir") == "I"))
            some = some | (same if e is None else same & (F.col("elabel") == e))
        adj = adj.where(some)
    return Start(vertices, adj.select("src", "dst", "elabel", "dir", F.col("dst_rank").alias("rank")), ranks, q.directed, g.simple)


def count_columns(k: int, kind: str = "x") -> list[str]:
    return [f"{kind}{j}" for j in range(1, k + 1)]


def count_tests(s: Start, elabels: list[str] | None = None, rank: str = "rank") -> dict[str, Column]:
    """The counts of a vertex's edges: name to what an edge must be. x: by the neighbour's rank; e, i, o: by edge label."""
    tests = {c: F.col(rank) == j for j, c in enumerate(count_columns(len(s.ranks)), 1)}
    for j, e in enumerate(elabels or [], 1):
        same = F.col("elabel") == e
        tests[f"e{j}"] = same
        if s.directed:
            tests |= {f"{d}{j}": same & (F.col("dir") == d.upper()) for d in ("i", "o")}
    return tests


def one_hop(s: Start, elabels: list[str] | None = None) -> DataFrame:
    """(vid, vlabel, rank, x1..xk, pdeg [, e1..el, i1..il, o1..ol]) of all vertices of s, from one aggregation by src.

    pdeg counts incident edges; in simple undirected graphs that's the neighbours. With edge labels also counts of edges
    by label: all (e), and for directed graphs ingoing (i) and outgoing (o).
    """
    sums = [F.count(F.when(t, 1)).alias(c) for c, t in count_tests(s, elabels).items()]
    counted = s.adj.groupBy(F.col("src").alias("vid")).agg(*sums, F.count("*").alias("pdeg"))
    made = [c for c in counted.columns if c != "vid"]
    return s.vertices.join(counted, "vid", "left").select("vid", "vlabel", "rank", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in made))


def unrestricted_degree(g: LabeledGraph, features: DataFrame) -> DataFrame:
    """Add deg: all edges of a vertex, whatever the labels at their other ends (for full_degree)."""
    every = g.adjacency().groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"))
    return features.join(every, "vid", "left").withColumn("deg", F.coalesce("deg", F.lit(0)).cast("long"))


def with_mnd(features: DataFrame, s: Start) -> DataFrame:
    """Add mnd: the largest pdeg among the neighbours (0 without)."""
    near = s.adj.select("src", "dst").join(features.select(F.col("vid").alias("dst"), "pdeg"), "dst").groupBy(F.col("src").alias("vid")).agg(F.max("pdeg").alias("mnd"))
    return features.join(near, "vid", "left").withColumn("mnd", F.coalesce("mnd", F.lit(0)).cast("long"))


def reach(s: Start, hops: int) -> DataFrame:
    """(vid, other, at): the distance of every pair within `hops` hops in the label-pruned graph.

    For hops over one this can come near the square of a hub's neighbourhood; restrict s to survivors of one hop first.
    """
    adj = s.adj.select("src", "dst").distinct()
    seen = adj.select(F.col("src").alias("vid"), F.col("dst").alias("other"), F.lit(1).alias("at"))
    front = seen
    for h in range(2, hops + 1):
        far = front.select("vid", F.col("other").alias("src")).join(adj, "src").select("vid", F.col("dst").alias("other")).where("vid <> other").distinct()
        front = far.join(seen, ["vid", "other"], "left_anti").withColumn("at", F.lit(h))
        seen = seen.union(front)
    return seen


def hop_counts(s: Start, hops: int) -> DataFrame:
    """(vid, vlabel, rank, s<h>_<j>): how many vertices of rank j are at exactly h hops. Balls are sums over h."""
    far = reach(s, hops).join(s.vertices.select(F.col("vid").alias("other"), F.col("rank").alias("r")), "other")
    names = [(h, j) for h in range(1, hops + 1) for j in range(1, len(s.ranks) + 1)]
    counted = far.groupBy("vid").agg(*(F.count(F.when((F.col("at") == h) & (F.col("r") == j), 1)).alias(f"s{h}_{j}") for h, j in names))
    return s.vertices.join(counted, "vid", "left").select("vid", "vlabel", "rank", *(F.coalesce(f"s{h}_{j}", F.lit(0)).cast("long").alias(f"s{h}_{j}") for h, j in names))


# ---- predicates: (pattern, pattern vertex) to a Column over the features ----------------------------------------------

Test = Callable[[Pattern, str], Column]


def _x(q: Pattern) -> list[Column]:
    return [F.col(c) for c in count_columns(len(q.labels))]


def label(q: Pattern, u: str) -> Column:
    return F.col("vlabel") == q.vertices[u]


def degree(q: Pattern, u: str) -> Column:
    return label(q, u) & (F.col("pdeg") >= q.pdeg(u))


def full_degree(q: Pattern, u: str) -> Column:
    """The degree without regard to labels: what counting only pattern labels adds is the difference to degree()."""
    return label(q, u) & (F.col("deg") >= q.pdeg(u))


def mnd(q: Pattern, u: str) -> Column:
    return degree(q, u) & (F.col("mnd") >= q.mnd(u))


def nlf(q: Pattern, u: str) -> Column:
    out = label(q, u)
    for c, n in zip(_x(q), q.vector(u), strict=True):
        if n:
            out = out & (c >= n)
    return out


def mnd_nlf(q: Pattern, u: str) -> Column:
    return mnd(q, u) & nlf(q, u)


def code_lemma(q: Pattern, u: str) -> Column:
    """Degree and code at least the pattern's. Over the cap the degree alone decides, as it then must."""
    cap = q.max_degree
    own = codes.ncode_column(_x(q), cap)
    return degree(q, u) & ((F.col("pdeg") > q.pdeg(u)) | (own >= q.code(u)))


def code_strict(q: Pattern, u: str) -> Column:
    """Degree and code both larger, or both equal. A larger degree implies a larger code, so the code decides at equal degree."""
    own = codes.ncode_column(_x(q), q.max_degree)
    return label(q, u) & ((F.col("pdeg") > q.pdeg(u)) | ((F.col("pdeg") == q.pdeg(u)) & (own == q.code(u))))


def code_log(slack: float = 1e-9) -> Test:
    """code_lemma by logarithms of codes, compared loosely: rounding must lose no candidate, so smaller by `slack` (relative) still passes."""

    def test(q: Pattern, u: str) -> Column:
        want = codes.log_code(q.vector(u))
        return degree(q, u) & ((F.col("pdeg") > q.pdeg(u)) | (codes.ncode_log(_x(q)) >= want - slack * max(1.0, want)))

    return test


# ---- the tests that peeling uses, over arrays: (pattern, pattern vertex, rank of its label, columns by name) to a mask -----


def _plain_strict(q: Pattern, u: str, rank: int, f: dict[str, np.ndarray]) -> np.ndarray:
    same = f["pdeg"] == q.pdeg(u)
    for c, n in zip(count_columns(len(q.labels)), q.vector(u), strict=True):
        same = same & (f[c] == n)
    return (f["rank"] == rank) & ((f["pdeg"] > q.pdeg(u)) | same)


def _plain_nlf(q: Pattern, u: str, rank: int, f: dict[str, np.ndarray]) -> np.ndarray:
    out = f["rank"] == rank
    for c, n in zip(count_columns(len(q.labels)), q.vector(u), strict=True):
        out = out & (f[c] >= n)
    return out


code_strict.plain, nlf.plain = _plain_strict, _plain_nlf


def code_packets(width: int | None = None) -> Test:
    """Each packet of `width` labels passes the strict test: width 1 is nlf, the full width code_strict.

    None: the widest packets whose codes fit 64 bits at the pattern's largest degree, over which codes aren't looked at.
    """

    def test(q: Pattern, u: str) -> Column:
        x, y, out = _x(q), q.vector(u), label(q, u)
        step = width or max(1, min(len(x), codes.max_width(q.max_degree)))
        for k in range(0, len(x), step):
            part, want = x[k : k + step], y[k : k + step]
            total, need = sum(part[1:], part[0]), sum(want)
            own = codes.ncode_column(part, q.max_degree)
            out = out & ((total > need) | ((total == need) & (own == codes.ncode(want))))
        return out

    return test


def _hop_columns(q: Pattern, h: int, up_to: bool) -> list[Column]:
    k = len(q.labels)
    each = lambda j: [F.col(f"s{i}_{j}") for i in range(1 if up_to else h, h + 1)]
    return [sum(each(j)[1:], each(j)[0]) for j in range(1, k + 1)]


def _at_least(x: list[Column], want: list[int]) -> Column:
    """The code of x is at least that of want, by totals where these differ."""
    total, need = sum(x[1:], x[0]), sum(want)
    return (total > need) | ((total == need) & (codes.ncode_column(x, need) >= codes.ncode(want)))


def ball(hops: int) -> Test:
    """The code of all vertices within `hops` hops. Sound: images only gain vertices within a distance."""
    return lambda q, u: label(q, u) & _at_least(_hop_columns(q, hops, True), q.ball(u, hops))


def nested_balls(hops: int) -> Test:
    def test(q: Pattern, u: str) -> Column:
        out = label(q, u)
        for h in range(1, hops + 1):
            out = out & _at_least(_hop_columns(q, h, True), q.ball(u, h))
        return out

    return test


def shell(hops: int, degree_only: bool = False) -> Test:
    """Codes at exactly 1 to `hops` hops. Not sound, as images may come closer: opt in, and measure what is lost."""

    def test(q: Pattern, u: str) -> Column:
        out = label(q, u)
        for h in range(1, hops + 1):
            x, want = _hop_columns(q, h, False), q.ball(u, h, exactly=True)
            out = out & (sum(x[1:], x[0]) >= sum(want) if degree_only else _at_least(x, want))
        return out

    return test


def shell_packed(hops: int) -> Test:
    """Codes at exactly 1 to `hops` hops, packed to one code and compared as one: at least the pattern's. Opt in, as shell()."""

    def test(q: Pattern, u: str) -> Column:
        parts = [codes.ncode_column(_hop_columns(q, h, False)) for h in range(1, hops + 1)]
        return label(q, u) & (codes.ncode_column(parts) >= codes.ncode([codes.ncode(q.ball(u, h, exactly=True)) for h in range(1, hops + 1)]))

    return test


def edge_vectors(q: Pattern, u: str, elabels: list[str]) -> tuple[list[int], list[int], list[int]]:
    """(all, ingoing, outgoing) counts of u's edges by label."""
    every, into, out = ([0] * len(elabels) for _ in range(3))
    for a, b, e in q.edges:
        if u in (a, b) and e in elabels:
            every[elabels.index(e)] += 1
            (into if b == u else out)[elabels.index(e)] += 1
    return every, into, out


def edge_aware(elabels: list[str], directed: bool = False, packed: bool = False) -> Test:
    """Vertex-label code and edge-label code (two for directed graphs) of one vertex.

    Part by part the strict test applies at equal degree. packed: the parts are first packed to one code, which at equal
    degree must be equal as well; the packed form is compared only there, where it is small.
    """

    def test(q: Pattern, u: str) -> Column:
        kinds = ("i", "o") if directed else ("e",)
        every, into, out = edge_vectors(q, u, elabels)
        wants = [q.vector(u), *([into, out] if directed else [every])]
        columns = [_x(q), *([F.col(c) for c in count_columns(len(elabels), kind)] for kind in kinds)]
        parts = [codes.ncode_column(c, q.max_degree) for c in columns]
        goal = [codes.ncode(w) for w in wants]
        if packed:
            same = codes.ncode_column(parts) == codes.ncode(goal)
        else:
            same = F.lit(True)
            for p, w in zip(parts, goal, strict=True):
                same = same & (p == w)
        more = F.col("pdeg") > q.pdeg(u)
        if directed:  # each direction's edges are at least the pattern's
            more = more & (sum(columns[1][1:], columns[1][0]) >= sum(into)) & (sum(columns[2][1:], columns[2][0]) >= sum(out))
        return label(q, u) & (more | ((F.col("pdeg") == q.pdeg(u)) & same))

    def plain(q: Pattern, u: str, rank: int, f: dict[str, np.ndarray]) -> np.ndarray:
        every, into, out = edge_vectors(q, u, elabels)
        wants = {"x": q.vector(u)} | ({"i": into, "o": out} if directed else {"e": every})
        same, more = f["pdeg"] == q.pdeg(u), f["pdeg"] > q.pdeg(u)
        for kind, want in wants.items():
            columns = [f[c] for c in count_columns(len(want), kind)]
            for c, n in zip(columns, want, strict=True):
                same = same & (c == n)
            if kind in "io":
                more = more & (sum(columns) >= sum(want))
        return (f["rank"] == rank) & (more | same)

    test.plain = plain
    return test


def edge_labels(q: Pattern) -> list[str] | None:
    """The edge labels that edge-aware codes of q count; None where an edge of q may have any label, as counts would mislead."""
    names = {e for _, _, e in q.edges}
    return None if None in names or not names else sorted(names)


def code_for(q: Pattern) -> tuple[Test, list[str] | None]:
    """(the code test that fits q, the edge labels it counts): edge-aware, in each direction where q is directed, or plain."""
    names = edge_labels(q)
    return (code_strict, None) if names is None else (edge_aware(names, q.directed), names)


def candidates(features: DataFrame, q: Pattern, test: Test, extra: list[str] | None = None) -> DataFrame:
    """(u, vid): every pair that passes. One pass over the features, without a join."""
    passed = F.filter(F.array(*(F.when(test(q, u), F.lit(u)) for u in sorted(q.vertices))), lambda u: u.isNotNull())
    return features.select(F.explode(passed).alias("u"), "vid", *(extra or []))


def any_match(q: Pattern, test: Test) -> Column:
    out = F.lit(False)
    for u in sorted(q.vertices):
        out = out | test(q, u)
    return F.coalesce(out, F.lit(False))


def restricted(s: Start, keep: DataFrame) -> Start:
    """s on the vertices of keep (vid)."""
    return Start(s.vertices.join(keep.select("vid"), "vid", "left_semi"), both_ends(s.adj, keep), s.ranks, s.directed, s.simple)
