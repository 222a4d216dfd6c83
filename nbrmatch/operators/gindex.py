"""Codes of whole graphs, for databases of many small graphs (graph_id in front of vertices and edges)."""

from __future__ import annotations

import hashlib

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codes import labeled_code, ncode, ncode_column
from ..session import cut
from . import search
from .pattern import Pattern


def vertex_codes(vertices: DataFrame, edges: DataFrame, labels: list[str]) -> DataFrame:
    """(graph_id, vid, rank, code, own): own folds the label into the code. Labels outside `labels` count as rank 0.

    One aggregation by (graph_id, vid); a label vector needs sums small enough for 64 bits, as small graphs have.
    """
    ranks = {n: k for k, n in enumerate(sorted(labels), 1)}
    rank = F.lit(0)
    for n, k in ranks.items():
        rank = F.when(F.col("vlabel") == n, k).otherwise(rank)
    ranked = vertices.select("graph_id", "vid", rank.alias("rank"))
    both = edges.select("graph_id", "src", "dst").union(edges.select("graph_id", F.col("dst"), F.col("src"))).distinct()
    near = both.join(ranked.select("graph_id", F.col("vid").alias("dst"), F.col("rank").alias("r")), ["graph_id", "dst"])
    counted = near.groupBy("graph_id", F.col("src").alias("vid")).agg(*(F.count(F.when(F.col("r") == k, 1)).alias(f"x{k}") for k in ranks.values()))
    full = ranked.join(counted, ["graph_id", "vid"], "left")
    code = ncode_column([F.coalesce(f"x{k}", F.lit(0)) for k in ranks.values()])
    return full.select("graph_id", "vid", "rank", code.alias("code")).withColumn("own", labeled_code(F.col("rank"), F.col("code")))


def graph_codes(coded: DataFrame) -> DataFrame:
    """(graph_id, n_vertices, digits, digest): the code over all vertex codes, sorted so that numbering doesn't matter.

    The numbers get huge; their decimal digits are counted and a digest stands for them.
    """

    def one(group: pd.DataFrame) -> pd.DataFrame:
        code = ncode(sorted(int(x) for x in group["own"]))
        digits = len(str(code)) if code < 10**4000 else int(code.bit_length() * 0.30103) + 1
        return pd.DataFrame({"graph_id": [group["graph_id"].iloc[0]], "n_vertices": [len(group)], "digits": [digits], "digest": [hashlib.sha256(code.to_bytes((code.bit_length() + 8) // 8, "big")).hexdigest()]})

    return coded.select("graph_id", "own").groupBy("graph_id").applyInPandas(one, "graph_id long, n_vertices long, digits long, digest string")


def collisions(coded: DataFrame) -> DataFrame:
    """(digests, shared, signatures): digests of graphs, how many have graphs that differ in their sorted vertex codes, and those in all."""
    listed = coded.groupBy("graph_id").agg(F.sort_array(F.collect_list("own")).alias("codes"))  # graphs of a database are small
    per = graph_codes(coded).join(listed, "graph_id").groupBy("digest").agg(F.countDistinct("codes").alias("n"))
    return per.agg(F.count("*").alias("digests"), F.sum((F.col("n") > 1).cast("long")).alias("shared"), F.sum("n").alias("signatures"))


def equal_groups(coded: DataFrame) -> DataFrame:
    """(digest, n): how many graphs share a code."""
    return graph_codes(coded).groupBy("digest").agg(F.count("*").alias("n"))


def lookup(coded: DataFrame, digest: str) -> DataFrame:
    return graph_codes(coded).where(F.col("digest") == digest).select("graph_id")


def may_contain(coded: DataFrame, q: Pattern, labels: list[str]) -> DataFrame:
    """(graph_id): graphs that can contain q: for each label, the k-th largest code is at least the pattern's k-th largest.

    Sound, as an image's code is at least its pattern vertex's, and images are distinct. The k-th largest code is at least
    c where k codes are, so one aggregation of counts by graph decides, and no graph's codes are listed.
    """
    ranks = {n: k for k, n in enumerate(sorted(labels), 1)}
    enough, sums = F.lit(True), []
    for n in q.labels:
        want = sorted((ncode(q.vector(u, ranks)) for u in q.vertices if q.vertices[u] == n), reverse=True)
        for k, c in enumerate(want, 1):
            name = f"n{len(sums)}"
            sums.append(F.count(F.when((F.col("rank") == ranks.get(n, -1)) & (F.col("code") >= c), 1)).alias(name))
            enough = enough & (F.col(name) >= k)
    return coded.groupBy("graph_id").agg(*sums).where(enough).select("graph_id")


def containment(vertices: DataFrame, edges: DataFrame, q: Pattern) -> DataFrame:
    """(graph_id, n): graphs that contain q and how many embeddings; the key filters, the search then confirms.

    Vertices and edges without the pattern's labels are left out first; what remains, and what the key leaves of it, is
    written once.
    """
    v = cut(vertices.where(F.col("vlabel").isin(q.labels)).select("graph_id", "vid", "vlabel"), "graph-v")
    side = lambda c: v.select("graph_id", F.col("vid").alias(c))
    e = cut(edges.join(side("src"), ["graph_id", "src"], "left_semi").join(side("dst"), ["graph_id", "dst"], "left_semi").select("graph_id", "src", "dst", "elabel"), "graph-e")
    kept = cut(may_contain(vertex_codes(v, e, q.labels), q, q.labels), "graph-ids")
    v, e = v.join(kept, "graph_id", "left_semi"), e.join(kept, "graph_id", "left_semi")
    adj = cut(e.union(e.select("graph_id", "dst", "src", "elabel")).distinct(), "graph-adj")
    sequence, rows, placed = search.order(q, how="bfs"), None, []
    for u in sequence:
        own = v.where(F.col("vlabel") == q.vertices[u]).select("graph_id", F.col("vid").alias(f"m_{u}"))
        rows = own if rows is None else rows.join(own, "graph_id") if not any(w in placed for w in q.neighbours(u)) else rows
        for k, w in enumerate(sorted({w for w in q.neighbours(u) if w in placed}, key=placed.index)):
            e = next(x[2] for x in q.edges if {x[0], x[1]} == {u, w})
            t = adj.where(F.lit(True) if e is None else F.col("elabel") == e).select("graph_id", F.col("src").alias(f"m_{w}"), F.col("dst").alias(f"m_{u}")).distinct()
            rows = rows.join(t, ["graph_id", f"m_{w}"]).join(own, ["graph_id", f"m_{u}"], "left_semi") if k == 0 else rows.join(t, ["graph_id", f"m_{w}", f"m_{u}"], "left_semi")
        for w in placed:
            if q.vertices[w] == q.vertices[u]:
                rows = rows.where(F.col(f"m_{w}") != F.col(f"m_{u}"))
        placed.append(u)
    return rows.groupBy("graph_id").agg(F.count("*").alias("n"))
