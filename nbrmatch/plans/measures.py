"""Cost and accuracy measures of filters, searches and stored structures."""

from __future__ import annotations

import statistics
import threading
import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, filters, fixpoint
from ..operators.graph import LabeledGraph
from ..operators.pattern import Pattern
from ..session import written_bytes


def round_log(spark: SparkSession, p: fixpoint.Peeled) -> DataFrame:
    return spark.createDataFrame(p.log or [], "round int, checked long, removed long, by_degree long, by_code long")


def search_space(cand: DataFrame) -> DataFrame:
    """(u, n, log10): candidates of each pattern vertex; the sum of log10 is that of the product."""
    return cand.groupBy("u").agg(F.count("*").alias("n")).select("u", "n", F.round(F.log10("n"), 6).alias("log10"))


TESTS: dict[str, filters.Test] = {
    "label": filters.label, "degree": filters.degree, "mnd": filters.mnd, "nlf": filters.nlf, "mnd_nlf": filters.mnd_nlf, "lemma": filters.code_lemma, "strict": filters.code_strict,
}


def pairs_per_filter(features: DataFrame, q: Pattern) -> DataFrame:
    """(filter, pairs, vertices) left by each filter, all counted in one pass over the features (with mnd)."""
    sums = []
    for name, test in TESTS.items():
        hits = [F.coalesce(test(q, u), F.lit(False)).cast("long") for u in sorted(q.vertices)]
        total = sum(hits[1:], hits[0])
        sums.append(F.struct(F.lit(name).alias("filter"), F.sum(total).alias("pairs"), F.sum((total > 0).cast("long")).alias("vertices")).alias(name))
    return features.agg(*sums).select(F.inline(F.array(*TESTS)))


def _images(embeddings: DataFrame) -> DataFrame:
    pairs = F.explode(F.array(*(F.struct(F.lit(c[2:]).alias("u"), F.col(c).alias("vid")) for c in embeddings.columns)))
    return embeddings.select(pairs.alias("p")).select("p.u", "p.vid").distinct()


def precision(cand: DataFrame, embeddings: DataFrame) -> DataFrame:
    """(u, candidates, images, precision_, all_images): candidates that take part in an embedding; images must equal all_images."""
    images = _images(embeddings).withColumn("hit", F.lit(1))
    every = images.groupBy("u").agg(F.count("*").alias("all_images"))
    per = cand.join(images, ["u", "vid"], "left").groupBy("u").agg(F.count("*").alias("candidates"), F.count("hit").alias("images"))
    return per.join(every, "u", "left").select("u", "candidates", "images", F.round(F.col("images") / F.col("candidates"), 6).alias("precision_"), F.coalesce("all_images", F.lit(0)).alias("all_images"))


def recall(cand: DataFrame, embeddings: DataFrame) -> DataFrame:
    """(images, kept) over all pattern vertices: equal for sound filters."""
    images = _images(embeddings)
    return images.join(cand.select("u", "vid").withColumn("hit", F.lit(1)), ["u", "vid"], "left").agg(F.count("*").alias("images"), F.count("hit").alias("kept"))


def collisions(features: DataFrame, code: Column, vector: list[str]) -> DataFrame:
    """(collisions): codes that more than one vector has."""
    distinct = features.select(code.alias("code"), *vector).distinct()
    return distinct.groupBy("code").agg(F.count("*").alias("n")).agg(F.coalesce(F.sum((F.col("n") > 1).cast("long")), F.lit(0)).alias("collisions"))


def digits(coded: DataFrame) -> DataFrame:
    return coded.groupBy(F.length(F.col("code").cast("string")).cast("long").alias("digits")).agg(F.count("*").alias("n"))


def stored_bytes(tables: list[DataFrame]) -> int:
    """Bytes of the files that cut() wrote for these tables."""
    return sum(written_bytes(t) for t in tables if t.__dict__.get("_written"))


def stored(spark: SparkSession, g: LabeledGraph, q: Pattern) -> DataFrame:
    """(engine, vertices, edge_rows, bytes): what the peeled graph and the tree index keep for the search, as written to files."""
    p = fixpoint.peel(filters.start(g, q), q)
    index = baselines.tree_index(g, q)
    rows = index.rows().agg(F.sum("n")).first()[0] or 0
    own = ("peeled", p.state.count(), p.adj.count() // 2, stored_bytes([p.state, p.adj]))
    return spark.createDataFrame([own, ("tree_index", index.cand.count(), rows, stored_bytes([index.cand, *index.tables.values()]))], "engine string, vertices long, edge_rows long, bytes long")


def comparisons(q: Pattern, vertices: int, width: int | None = None) -> dict[str, int]:
    """Comparisons that a filter makes for all pairs: codes one each, packets one for each packet, label frequency one for each label."""
    pairs, k = vertices * len(q.vertices), len(q.labels)
    return {"code": pairs, "mnd": pairs, "packets": pairs * -(-k // (width or k)), "nlf": pairs * k}


def timed(runs: list[Callable[[], object]], spark: SparkSession, deadline_s: float = 60.0, group: str = "timed") -> dict:
    """Seconds of each run: mean, median, or status INF once the set's deadline has passed and its jobs are cancelled."""
    times, began = [], time.monotonic()
    sc = spark.sparkContext
    timer = threading.Timer(deadline_s, lambda: sc.cancelJobGroup(group))
    sc.setJobGroup(group, group, interruptOnCancel=True)
    timer.start()
    try:
        for run in runs:
            if time.monotonic() - began > deadline_s:
                return {"status": "INF", "runs": len(times)}
            t = time.perf_counter()
            try:
                run()
            except Exception as e:
                if "cancel" in str(e).lower():
                    return {"status": "INF", "runs": len(times)}
                raise
            times.append(time.perf_counter() - t)
    finally:
        timer.cancel()
        sc.setLocalProperty("spark.jobGroup.id", None)
    return {"status": "ok", "runs": len(times), "mean_s": statistics.fmean(times), "median_s": statistics.median(times)}
