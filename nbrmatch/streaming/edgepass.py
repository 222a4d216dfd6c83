"""Filtering while edges are read once, and edges that arrive as a stream."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.filters import Start, any_match, code_strict, count_columns, one_hop, rank_column
from ..operators.fixpoint import restricted_adj
from ..operators.pattern import Pattern
from ..session import cut, discard, shared_dir


def prefilter(s: Start, q: Pattern) -> Start:
    """One pass over the edges, grouped by source: a vertex stays with its edges if its degree and code match some u.

    Counting is one aggregation, so hubs are never gathered; edges to dropped vertices go as well.
    """
    s = Start(s.vertices, cut(s.adj, "adj"), s.ranks, s.directed, s.simple)
    kept = cut(one_hop(s).where(any_match(q, code_strict)).select("vid", "vlabel", "rank"), "pass-kept")
    return Start(kept, cut(restricted_adj(s.adj, kept), "pass-adj"), s.ranks, s.directed, s.simple)


def _passes(q: Pattern, ranks: dict[str, int]) -> dict[int, list[tuple[int, list[int]]]]:
    """By rank of a vertex's own label: (degree, counts) of the pattern vertices with this label."""
    out: dict[int, list[tuple[int, list[int]]]] = {}
    for u, n in q.vertices.items():
        out.setdefault(ranks[n], []).append((q.pdeg(u), q.vector(u, ranks)))
    return out


def sorted_pass(s: Start, q: Pattern) -> DataFrame:
    """(src, dst, elabel): the edges of kept vertices, by reading edges sorted by source with one open vertex in memory.

    All edges of a source are in one partition, sorted, and read in batches of columns. Sources that end in a batch are
    judged by their counts at its group boundaries. The source that is still open keeps its counts and its edges, unless
    its degree passes that of some pattern vertex of its label: then it is certain to stay and its edges are handed on.
    Vertices without edges never appear.
    """
    k, wanted = len(s.ranks), _passes(q, s.ranks)
    own = s.vertices.select(F.col("vid").alias("src"), F.col("rank").alias("src_rank"))
    edges = s.adj.join(own, "src").select("src", "dst", "elabel", "rank", "src_rank")
    dealt = edges.repartitionByRange("src").sortWithinPartitions("src", "dst")
    names = ["src", "dst", "elabel"]

    def stays(rank: np.ndarray, x: np.ndarray) -> np.ndarray:
        """Of vertices (rank, counts) those that pass; a degree over a pattern vertex's is enough whatever follows."""
        n, out = x.sum(axis=1), np.zeros(len(x), dtype=bool)
        for r, ways in wanted.items():
            for d, y in ways:
                out |= (rank == r) & ((n > d) | ((n == d) & (x == np.array(y)).all(axis=1)))
        return out

    least = {r: min(d for d, _ in ways) for r, ways in wanted.items()}

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held, counts, rank = [], np.zeros(k, dtype=np.int64), 0  # of the open source
        current = None
        for batch in batches:
            if not len(batch):
                continue
            src, r = batch.src.to_numpy(), batch["rank"].to_numpy()
            starts = np.concatenate([[0], np.flatnonzero(src[1:] != src[:-1]) + 1])
            x = np.zeros((len(starts), k), dtype=np.int64)
            np.add.at(x, (np.repeat(np.arange(len(starts)), np.diff([*starts, len(src)])), r - 1), 1)
            own_rank = batch.src_rank.to_numpy()[starts]
            goes_on = src[0] == current
            if held and not goes_on and stays(np.array([rank]), counts[None])[0]:
                yield from held
            if goes_on:
                x[0] += counts
            else:
                held = []
            keep = stays(own_rank, x)
            sure = x[-1].sum() > least.get(int(own_rank[-1]), 1 << 60)
            keep[-1] = sure  # the last source is open: only its degree can tell already
            if goes_on and len(starts) > 1 and keep[0] or goes_on and len(starts) == 1 and sure:
                yield from held
            if goes_on and (len(starts) > 1 or sure):
                held = []
            yield batch.loc[np.repeat(keep, np.diff([*starts, len(src)])), names]
            if len(starts) > 1:
                held = []
            if not sure:
                held.append(batch.iloc[starts[-1] :][names])
            current, counts, rank = src[-1], x[-1], int(own_rank[-1])
        if held and stays(np.array([rank]), counts[None])[0]:
            yield from held

    found = cut(dealt.mapInPandas(run, "src long, dst long, elabel string"), "sorted-pass")
    return found.join(found.select(F.col("src").alias("dst")).distinct(), "dst", "left_semi").select("src", "dst", "elabel")


def random_pass(edges: DataFrame, vertices: DataFrame, q: Pattern, batches: int = 4) -> tuple[DataFrame, list[dict]]:
    """Edges that arrive in any order, in batches: counts of label-pruned vertices merge; the verdict falls at the end.

    Returns (kept vid, and for each batch how many edges and vertices are held). Compare with sorted_pass, whose
    verdicts fall vertex by vertex.
    """
    ranks = q.ranks()
    v = vertices.where(F.col("vlabel").isin(*ranks)).select("vid", "vlabel", rank_column(F.col("vlabel"), ranks).alias("rank"))
    xs, held, state = count_columns(len(ranks)), [], None
    part = F.pmod(F.xxhash64("src", "dst"), F.lit(batches)).cast("int")
    dealt = cut(edges.select("src", "dst", part.alias("part")), "arrivals", "part")  # a batch reads its own folder
    for b in range(batches):
        some = dealt.where(F.col("part") == b)
        both = some.select("src", "dst").union(some.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        near = both.join(v.select(F.col("vid").alias("dst"), "rank"), "dst").join(v.select(F.col("vid").alias("src")), "src", "left_semi")
        counted = near.groupBy(F.col("src").alias("vid")).agg(*(F.count(F.when(F.col("rank") == j, 1)).alias(c) for j, c in enumerate(xs, 1)), F.count("*").alias("pdeg"))
        merged = counted if state is None else state.union(counted).groupBy("vid").agg(*(F.sum(c).alias(c) for c in (*xs, "pdeg")))
        before, state = state, cut(merged, "random-pass")
        discard(before)
        row = state.agg(F.count("*"), F.coalesce(F.sum("pdeg"), F.lit(0))).first()
        held.append({"batch": b, "vertices": row[0], "edges": row[1] // 2})
    discard(dealt)
    full = v.join(state, "vid", "left").select("vid", "vlabel", "rank", *(F.coalesce(c, F.lit(0)).alias(c) for c in (*xs, "pdeg")))
    return full.where(any_match(q, code_strict)).select("vid"), held


def live_counts(edges: DataFrame, vertices: DataFrame, q: Pattern) -> DataFrame:
    """A streaming aggregation over edges (src, dst): (vid, vlabel, x1..xk, pdeg) of pattern-labelled vertices, updated by trigger.

    vertices: a static table. Only counts are state, so it grows with the kept vertices, not with their edges. In a
    stream that only adds edges a vertex that passes stays passed, so "keep" may be reported at once (`kept`), while a
    vertex that doesn't pass yet is only dropped when the stream is sealed.
    """
    ranks = q.ranks()
    v = vertices.where(F.col("vlabel").isin(*ranks)).select("vid", "vlabel", rank_column(F.col("vlabel"), ranks).alias("rank"))
    both = edges.select(F.explode(F.array(F.struct(F.col("src").alias("a"), F.col("dst").alias("b")), F.struct(F.col("dst").alias("a"), F.col("src").alias("b")))).alias("e")).select("e.a", "e.b")
    near = both.join(v.select(F.col("vid").alias("b"), F.col("rank").alias("r")), "b").join(v.select(F.col("vid").alias("a"), "vlabel"), "a")
    xs = count_columns(len(ranks))
    counted = near.groupBy(F.col("a").alias("vid"), "vlabel").agg(*(F.count(F.when(F.col("r") == j, 1)).alias(c) for j, c in enumerate(xs, 1)), F.count("*").alias("pdeg"))
    return counted.withColumn("kept", any_match(q, code_strict))


#: State of streams lies in files beside the executors' heaps, which it would outgrow.
_STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled": "true",
    "spark.sql.streaming.stateStore.rocksdb.trackTotalNumberOfRows": "false",
}


def _run(spark, writer) -> None:
    """Start the stream with state in files, and wait until it has read what is there now."""
    before = {k: spark.conf.get(k, None) for k in _STATE}
    for k, v in _STATE.items():
        spark.conf.set(k, v)
    try:
        running = writer.trigger(availableNow=True).start()  # it has its own copy of the settings
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    try:
        running.awaitTermination()
    finally:
        running.stop()


def run_to_memory(stream: DataFrame, name: str) -> DataFrame:
    """Run a stream over what is there now, into a memory table of all its rows. For few rows: the driver holds them."""
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _run(spark, stream.writeStream.outputMode("complete").format("memory").queryName(name).option("checkpointLocation", path))
    return spark.table(name)


def run_to_files(stream: DataFrame, name: str) -> DataFrame:
    """Run a stream over what is there now and read its rows, each written once, from files that the executors write."""
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _run(spark, stream.writeStream.outputMode("append").format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/checkpoint"))
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


#: Later than any event.
END = "9999-01-01"


def ended(stream: DataFrame, ts: str = "ts") -> DataFrame:
    """The stream and an end mark: a row of nulls at END, in the same batch, so that the watermark then passes all other rows.

    Only for a stream that has no more rows to come: later ones would be late.
    """
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/end-{uuid.uuid4().hex}"
    mark = spark.range(1).select(*((F.lit(END) if n == ts else F.lit(None)).cast(t).alias(n) for n, t in stream.dtypes))
    mark.write.parquet(path)
    return stream.union(spark.readStream.schema(mark.schema).parquet(path))


def event_stream(spark, sf_dir: str) -> DataFrame:
    """The events table as a file stream, its times with a zone, as watermarks need."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    folder, name = path.rsplit("/", 1)
    if not spark.read.parquet(path).inputFiles()[0].rstrip("/").endswith(name):
        source = spark.readStream.schema(schema).parquet(path)
    else:
        source = spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder)
    return source.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_counts(events: DataFrame, size: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(w, "event_type").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("window"), "user_id").agg(F.count("*").alias("n"))


def followed_by(events: DataFrame, first: str, then: str, within: str, late: str = "1 hour") -> DataFrame:
    """(<first>_id, <then>_id): events of one user and two types, the second at most `within` after the first. A join of two streams."""
    of = lambda kind: events.where(F.col("event_type") == kind).select(F.col("event_id").alias(f"{kind}_id"), F.col("user_id").alias(f"{kind}_user"), F.col("ts").alias(f"{kind}_ts")).withWatermark(f"{kind}_ts", late)
    after = (F.col(f"{then}_ts") >= F.col(f"{first}_ts")) & (F.col(f"{then}_ts") <= F.col(f"{first}_ts") + F.expr(f"interval {within}"))
    return of(first).join(of(then), (F.col(f"{first}_user") == F.col(f"{then}_user")) & after).select(f"{first}_id", f"{then}_id")
