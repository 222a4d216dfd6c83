"""Peeling: vertices that match no pattern vertex go, which lowers their neighbours' counts, until nothing changes.

The vertices left are the same in whatever order they go, as counts only fall and a failed vertex never passes again; so
whole rounds are set operations. There are two kinds of rounds. One that removes many vertices rewrites what is left. One
that removes few reads and writes only what it touches: state and adjacency lie in folders by a hash of the vertex, and
such a round reads the folders of removed vertices (adjacency) and of their neighbours (state), and notes the touched
vertices' new rows in a small table beside the state. These notes are merged into one table now and then.

A label-pruned graph of at most SMALL_ROWS vertices and adjacency rows (both are counted first) needs no rounds of jobs:
`auto` runs the same rounds over arrays on the driver, with the same result and log.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import SMALL_ROWS, cut, discard
from .filters import Start, Test, any_match, candidates, code_strict, count_columns, count_tests, label, one_hop
from .pattern import Pattern

#: Rows of a folder of state or adjacency, about, and the most folders there are.
FOLDER_ROWS, FOLDERS = 2_000_000, 1024
#: A round that removes a smaller share of the vertices than this touches its own folders only.
FEW = 0.05
#: Notes that pile up before they are merged.
NOTES = 8


@dataclass
class Peeled:
    """state: (vid, vlabel, rank, x1..xk, ..., pdeg) of what is left; adj between these; log: one dict for each round."""

    state: DataFrame
    adj: DataFrame
    log: list[dict]
    start: Start
    engine: str = "frontier"


def _by_degree(q: Pattern):
    """Fails the degree against every pattern vertex of its label."""
    some = F.lit(False)
    for u in sorted(q.vertices):
        some = some | (label(q, u) & (F.col("pdeg") >= q.pdeg(u)))
    return ~F.coalesce(some, F.lit(False))


def _folder(column: str, folders: int) -> Column:
    return F.pmod(F.xxhash64(column), F.lit(folders)).cast("int")


def _read(table: DataFrame, folders: list[int], all_folders: int) -> DataFrame:
    """The rows of some folders: a filter on the partition column, so other files aren't opened."""
    return table if len(folders) == all_folders else table.where(F.col("folder").isin(folders))


def _ids(df: DataFrame, n: int) -> DataFrame:
    """df, broadcast if it has few rows."""
    return F.broadcast(df) if n <= SMALL_ROWS else df


def peel(s: Start, q: Pattern, test: Test = code_strict, max_rounds: int | None = None, engine: str = "auto", elabels: list[str] | None = None) -> Peeled:
    """engine: frontier looks at touched vertices, full at all of them in every round; auto is arrays where the graph is
    small, else frontier. Peeled.engine says which ran. Stopping early is sound.

    test must depend on label, counts and pdeg alone. elabels: edge labels that are counted too (filters.edge_aware).
    """
    counted = count_tests(s, elabels)
    rows = ["vid", "vlabel", "rank", *counted, "pdeg"]
    adj = cut(s.adj, "adj")
    s = Start(s.vertices, adj, s.ranks, s.directed, s.simple)
    if engine == "auto":
        if hasattr(test, "plain") and adj.count() <= SMALL_ROWS and s.vertices.limit(SMALL_ROWS + 1).count() <= SMALL_ROWS:
            return _in_arrays(s, q, test, max_rounds, elabels)
        engine = "frontier"
    state = cut(one_hop(s, elabels).select(*rows).withColumn("touched", F.lit(True)), "state")
    log: list[dict] = []
    foldered: tuple[DataFrame, DataFrame, int] | None = None  # state and adjacency in folders, and how many
    notes: list[DataFrame] = []
    looked, checked, left = state, None, state.count()
    while max_rounds is None or len(log) < max_rounds:
        see = looked if engine != "full" and foldered else looked.where("touched" if engine == "frontier" else "true")
        if engine == "full" and foldered:
            see = _current(foldered[0], notes, rows)
        gone = cut(see.where(~any_match(q, test)).select("vid", "rank", _by_degree(q).alias("degree")), "gone")
        seen = see.select(F.lit(None).cast("boolean").alias("degree"), F.lit(1).alias("s"))
        n, by_degree, checked = gone.select("degree", F.lit(0).alias("s")).union(seen).agg(F.coalesce(F.sum(1 - F.col("s")), F.lit(0)), F.coalesce(F.sum(F.col("degree").cast("long")), F.lit(0)), F.coalesce(F.sum("s"), F.lit(0))).first()
        if not n:
            discard(gone)
            break
        log.append({"round": len(log) + 1, "checked": checked, "removed": n, "by_degree": by_degree, "by_code": n - by_degree})
        few = n < FEW * left
        left -= n
        if not few and not foldered:
            before, state = state, cut(_without(state, adj, gone, n, counted, rows), "state")
            discard(before, gone)
            looked = state
            continue
        if not foldered:
            folders = max(1, min(FOLDERS, adj.count() // FOLDER_ROWS))
            spread = adj.withColumn("folder", _folder("dst", folders))
            spread = spread.repartition("folder", F.pmod(F.xxhash64("src"), F.lit(8))) if folders > 1 else spread
            foldered = (cut(state.select(*rows, _folder("vid", folders).alias("folder")), "state-folders", "folder"), cut(spread, "adj-folders", "folder"), folders)
            discard(state)
        base, edges, folders = foldered
        at = lambda t: [r[0] for r in t.select(_folder("vid", folders).alias("folder")).distinct().collect()]  # noqa: E731, B023  (FOLDERS rows at most)
        removed = gone.select(F.col("vid").alias("dst"), F.col("rank").alias("r"))
        lost = _read(edges, at(gone), folders).join(_ids(removed, n), "dst").groupBy(F.col("src").alias("vid")).agg(*_losses(counted))
        lost = cut(lost, "lost")
        touched_ids = _ids(lost.select("vid"), lost.count())
        now = _current(_read(base, at(lost), folders).join(touched_ids, "vid", "left_semi"), [x.join(touched_ids, "vid", "left_semi") for x in notes], rows)
        touched = now.join(gone.select("vid"), "vid", "left_anti").join(lost, "vid").select("vid", "vlabel", "rank", *((F.col(c) - F.col(f"d_{c}")).alias(c) for c in (*counted, "pdeg")))
        number = F.lit(len(log)).alias("round")
        dead = gone.select("vid", F.lit(None).cast("string").alias("vlabel"), "rank", *(F.lit(0).cast("long").alias(c) for c in (*counted, "pdeg")), number, F.lit(False).alias("alive"))
        note = cut(touched.select("*", number, F.lit(True).alias("alive")).union(dead), "note")
        discard(lost, gone)
        notes.append(note)
        looked = note.where("alive").drop("round", "alive")
        if len(notes) > NOTES:
            merged = cut(_latest(notes, rows), "note")
            discard(*notes[:-1])  # the last one is still looked at
            notes = [merged]
    kept = state.select(*rows) if not foldered else cut(_current(foldered[0], notes, rows), "state")
    if foldered:
        discard(*foldered[:2], *notes)
    return Peeled(kept, cut(restricted_adj(adj, kept, left), "kept-adj") if log else adj, log, s, engine)


def _in_arrays(s: Start, q: Pattern, test: Test, max_rounds: int | None, elabels: list[str] | None) -> Peeled:
    """peel() over arrays, for graphs whose size has been checked."""
    spark = s.adj.sparkSession
    vertices, adj = s.vertices.select("vid", "vlabel", "rank").orderBy("vid").toArrow(), s.adj.toArrow()
    vid, rank = (vertices[c].to_numpy() for c in ("vid", "rank"))
    src, dst = (np.searchsorted(vid, adj[c].to_numpy()) for c in ("src", "dst"))
    near, labels, dirs = adj["rank"].to_numpy(), np.array(adj["elabel"].to_pylist(), dtype=object), np.array(adj["dir"].to_pylist(), dtype=object)
    kinds: dict[str, np.ndarray] = {c: near == j for j, c in enumerate(count_columns(len(s.ranks)), 1)}
    for j, e in enumerate(elabels or [], 1):
        kinds[f"e{j}"] = labels == e
        if s.directed:
            kinds |= {f"{d}{j}": (labels == e) & (dirs == d.upper()) for d in ("i", "o")}
    counted = lambda at: {c: np.bincount(src[at & k], minlength=len(vid)) for c, k in (*kinds.items(), ("pdeg", np.ones(len(src), dtype=bool)))}
    f = {"rank": rank} | counted(np.ones(len(src), dtype=bool))
    alive, touched, log = np.ones(len(vid), dtype=bool), np.ones(len(vid), dtype=bool), []
    while max_rounds is None or len(log) < max_rounds:
        see, passes, degree = alive & touched, np.zeros(len(vid), dtype=bool), np.zeros(len(vid), dtype=bool)
        for u, name in q.vertices.items():
            passes |= test.plain(q, u, s.ranks[name], f)
            degree |= (rank == s.ranks[name]) & (f["pdeg"] >= q.pdeg(u))
        gone = see & ~passes
        n, by_degree = int(gone.sum()), int((gone & ~degree).sum())
        if not n:
            break
        log.append({"round": len(log) + 1, "checked": int(see.sum()), "removed": n, "by_degree": by_degree, "by_code": n - by_degree})
        alive &= ~gone
        lost = gone[dst]
        for c, less in counted(lost).items():
            f[c] = f[c] - less
        touched = np.zeros(len(vid), dtype=bool)
        touched[src[lost]] = True
    state = vertices.filter(pa.array(alive))
    for c in (*kinds, "pdeg"):
        state = state.append_column(c, pa.array(f[c][alive].astype(np.int64)))
    schema = s.vertices.select("vid", "vlabel", "rank").schema
    for c in (*kinds, "pdeg"):
        schema = schema.add(c, "long")
    left = adj.filter(pa.array(alive[src] & alive[dst])) if log else None
    kept = cut(spark.createDataFrame(state, schema=schema), "state")
    return Peeled(kept, s.adj if left is None else cut(spark.createDataFrame(left, schema=s.adj.schema), "kept-adj"), log, s, "arrays")


def _losses(counted: dict[str, Column]) -> list[Column]:
    """What a vertex loses with removed neighbours (of rank r): a sum for each count, and of edges."""
    return [*(F.count(F.when(t, 1)).alias(f"d_{c}") for c, t in counted.items()), F.count("*").alias("d_pdeg")]


def _without(state: DataFrame, adj: DataFrame, gone: DataFrame, n: int, counted: dict[str, Column], rows: list[str]) -> DataFrame:
    """All of the state after a round."""
    removed = gone.select(F.col("vid").alias("dst"), F.col("rank").alias("r"))
    lost = adj.join(_ids(removed, n), "dst").groupBy(F.col("src").alias("vid")).agg(*_losses(counted))
    left = state.join(_ids(gone.select("vid"), n), "vid", "left_anti").join(lost, "vid", "left")
    less = lambda c: (F.col(c) - F.coalesce(f"d_{c}", F.lit(0))).alias(c)
    return left.select(*rows[:3], *map(less, rows[3:]), F.col("d_pdeg").isNotNull().alias("touched"))


def _latest(notes: list[DataFrame], rows: list[str]) -> DataFrame:
    every = reduce(DataFrame.union, notes)
    if len(notes) == 1:
        return every
    return every.groupBy("vid").agg(F.max_by(F.struct(*rows[1:], "round", "alive"), "round").alias("s")).select("vid", "s.*")


def _current(base: DataFrame, notes: list[DataFrame], rows: list[str]) -> DataFrame:
    """The state's rows as the notes have changed them, without those that are gone."""
    if not notes:
        return base.select(*rows)
    latest = _latest(notes, rows)
    return base.select(*rows).join(latest.select("vid"), "vid", "left_anti").union(latest.where("alive").select(*rows))


def restricted_adj(adj: DataFrame, kept: DataFrame, n: int | None = None) -> DataFrame:
    """adj between kept vertices; n: how many there are, if known."""
    ids = kept.select("vid")
    side = lambda c: _ids(ids.withColumnRenamed("vid", c), SMALL_ROWS + 1 if n is None else n)
    return adj.join(side("src"), "src", "left_semi").join(side("dst"), "dst", "left_semi").select(*adj.columns)


def candidate_sizes(cand: DataFrame, q: Pattern) -> dict[str, int]:
    """How many candidates each pattern vertex has; as many rows as the pattern has vertices come to the driver."""
    return {u: 0 for u in q.vertices} | {r["u"]: r["n"] for r in cand.groupBy("u").agg(F.count("*").alias("n")).collect()}


def candidate_sets(p: Peeled, q: Pattern, test: Test = code_strict) -> DataFrame:
    return candidates(p.state, q, test)
