"""Edges that arrive live: a stream of placed orders, and state kept by vertex."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.codes import bump
from ..operators.filters import count_columns, rank_column
from ..operators.pattern import Pattern
from ..sources.graphs import vid


def order_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst, elabel, ts): customer-order edges, as the orders table's files appear."""
    path = f"{sf_dir}/orders.parquet"
    table = spark.read.parquet(path)
    folder, name = path.rsplit("/", 1)
    one_file = table.inputFiles()[0].rstrip("/").endswith(name)
    reader = spark.readStream.schema(table.schema)
    source = reader.option("pathGlobFilter", name).parquet(folder) if one_file else reader.parquet(path)
    return source.select(vid("customer", "o_custkey").alias("src"), vid("orders", "o_orderkey").alias("dst"), F.lit("placed").alias("elabel"), F.col("o_orderdate").cast("timestamp").alias("ts"))


#: Ids of vertices that share a state in stateful_counts: so many neighbouring ones at most.
RANGE = 4096


def stateful_counts(edges: DataFrame, idle: str = "30 days", width: int = RANGE) -> DataFrame:
    """(vid, n, sealed): edges of each dst vertex, from state of its own.

    A row is sent when edges come; a vertex is sealed, and its state dropped, when the watermark passes `idle` after its
    last edge. Needs (dst, ts). The states of a range of `width` ids lie in one group, as arrays, so that Python is called
    for a range and not for each vertex; a group can't outgrow its range.
    """

    def frame(key: tuple, vids: np.ndarray, n: np.ndarray, sealed: bool) -> pd.DataFrame:
        own = vids if not pd.isna(key[0]) else pd.array([None] * len(vids), dtype="Int64")  # edges without dst are one group
        return pd.DataFrame({"vid": own, "n": n, "sealed": np.full(len(vids), sealed)})

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        vids, n, last = (np.array(x, dtype=np.int64) for x in (state.get if state.exists else ((), (), ())))
        now = state.getCurrentWatermarkMs()
        seen = vids[:0]
        for b in batches if not state.hasTimedOut else ():
            ids, at = np.unique(b["dst"].to_numpy(dtype=np.int64), return_inverse=True)
            latest = np.full(len(ids), now, dtype=np.int64)
            np.maximum.at(latest, at, b["ms"].to_numpy(dtype=np.int64))
            every = np.union1d(vids, ids)
            more, until = np.zeros(len(every), dtype=np.int64), np.zeros(len(every), dtype=np.int64)
            old, new = np.searchsorted(every, vids), np.searchsorted(every, ids)
            more[old], until[old] = n, last
            more[new] += np.bincount(at, minlength=len(ids))
            until[new] = np.maximum(until[new], latest)
            vids, n, last, seen = every, more, until, np.union1d(seen, ids)
        if len(seen):
            yield frame(key, seen, n[np.searchsorted(vids, seen)], False)
        over = last + 1 < now
        if over.any():
            yield frame(key, vids[over], n[over], True)
            vids, n, last = vids[~over], n[~over], last[~over]
        if not len(vids):
            state.remove()
            return
        state.update((vids.tolist(), n.tolist(), last.tolist()))
        state.setTimeoutTimestamp(max(int(last.min()), now) + 1)

    own, ms = F.coalesce("dst", F.lit(0)).alias("dst"), F.coalesce(F.unix_millis("ts"), F.lit(0)).alias("ms")
    keyed = edges.select("dst", "ts").withWatermark("ts", idle).select(F.expr(f"dst div {width}").alias("range"), own, "ts", ms).groupBy("range")
    return keyed.applyInPandasWithState(update, "vid long, n long, sealed boolean", "vids array<long>, n array<long>, last array<long>", "append", GroupStateTimeout.EventTimeTimeout)


def live_filter(edges: DataFrame, vertices: DataFrame, q: Pattern, idle: str = "30 days") -> DataFrame:
    """(vid, x1..xk, pdeg, keep, sealed): verdicts on vertices with a pattern label while edges (src, dst, ts) arrive.

    Each vertex has state of its own: its label's rank, its neighbours by rank, and the code of these, which grows term by
    term with each neighbour. In a stream that only adds edges a vertex that passes stays, so keep is sent at once; that
    one doesn't pass is sent as it stands, and is final only when the watermark has passed `idle` after the vertex's last
    edge: then it is sealed and its state goes. Edges that come later than the watermark are dropped.
    """
    ranks = q.ranks()
    k, xs = len(ranks), count_columns(len(ranks))
    wanted: dict[int, list[tuple[int, int]]] = {}
    for u, n in q.vertices.items():
        wanted.setdefault(ranks[n], []).append((q.pdeg(u), q.code(u)))
    v = vertices.where(F.col("vlabel").isin(*ranks)).select("vid", rank_column(F.col("vlabel"), ranks).alias("rank"))
    ends = F.array(F.struct(F.col("src").alias("a"), F.col("dst").alias("b")), F.struct(F.col("dst").alias("a"), F.col("src").alias("b")))
    both = edges.select("ts", F.explode(ends).alias("e")).select("ts", "e.a", "e.b").withWatermark("ts", idle)
    near = both.join(v.select(F.col("vid").alias("b"), F.col("rank").alias("r")), "b").join(v.select(F.col("vid").alias("a"), "rank"), "a")

    def row(vid: int, rank: int, x: list[int], code: int, sealed: bool) -> pd.DataFrame:
        n = sum(x)
        keep = any(n > d or (n == d and code == c) for d, c in wanted.get(rank, ()))
        return pd.DataFrame([[vid, *x, n, keep, sealed]], columns=["vid", *xs, "pdeg", "keep", "sealed"])

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            rank, code, *x = state.get
            state.remove()
            yield row(key[0], rank, x, int(code), True)
            return
        rank, code, *x = state.get if state.exists else (0, "0", *[0] * k)
        code, last = int(code), 0
        for b in batches:
            for r, n in b["r"].value_counts().items():
                for _ in range(int(n)):
                    if sum(x) <= q.max_degree:  # over it the degree decides, and the code isn't looked at any more
                        code = bump(code, x, int(r))
                    x[int(r) - 1] += 1
            rank, last = int(b["rank"].iloc[0]), max(last, int(b["ts"].max().timestamp() * 1000))
        state.update((rank, str(code), *x))
        state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + 1)
        yield row(key[0], rank, x, code, False)

    counts = ", ".join(f"{c} long" for c in xs)
    return near.select("a", "ts", "r", "rank").groupBy("a").applyInPandasWithState(update, f"vid long, {counts}, pdeg long, keep boolean, sealed boolean", f"rank int, code string, {counts}", "append", GroupStateTimeout.EventTimeTimeout)
