"""Sharding by a two-pass external shuffle.

Pass one scatters rows into buckets small enough for memory, by a seeded hash of the whole row key (id and text), so a
hot id or source spreads evenly. Pass two permutes each bucket by Fisher-Yates with a seed of its own. Buckets one after
the other are the shuffled order; position p goes to shard p mod n as slot p div n, so shard counts differ by one at most.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialise

#: Buckets are numbered (group, bucket in group); there are at most so many groups, whatever the input.
GROUPS = 256


def fisher_yates(n: int, seed: int) -> np.ndarray:
    """A uniform permutation of range(n): numpy's shuffle is Fisher-Yates."""
    order = np.arange(n)
    np.random.default_rng(seed).shuffle(order)
    return order


def scatter(df: DataFrame, key: list[Column], buckets: int, seed: int) -> DataFrame:
    """Pass one's decision: columns _group and _bucket. Equal keys share a bucket; all others spread uniformly."""
    groups = max(1, min(GROUPS, buckets))
    h = F.xxhash64(F.lit(seed), *key)
    return df.withColumn("_group", F.pmod(h, F.lit(groups)).cast("int")).withColumn("_bucket", F.pmod(F.shiftright(h, 16), F.lit(-(-buckets // groups))).cast("int"))


def shuffle(df: DataFrame, key: list[str], bucket_bytes: int = 16 << 20, row_bytes: str = "size", seed: int = 42) -> DataFrame:
    """All rows of df, with their `position` in one uniform random order of the whole table (0 to n-1).

    key: columns that tell rows apart. Rows equal in them are put next to each other before the bucket is permuted, by
    their remaining columns; fully equal rows are interchangeable. The result depends on rows and seed alone, not on
    how the input is partitioned. Null keys hash as nulls. An empty table gives an empty one. Columns named _group,
    _bucket or position are replaced.
    """
    df = df.drop("_group", "_bucket", "position")
    total = df.agg(F.coalesce(F.sum(row_bytes), F.lit(0)).alias("n")).first()["n"]
    dealt = scatter(df, [F.col(c) for c in key], max(1, -(-int(total) // bucket_bytes)), seed)
    order = [*key, *(c for c in df.columns if c not in key)]
    names, schema = df.columns, ", ".join([*(f"`{n}` {t}" for n, t in df.dtypes), "_group int, _bucket int, _place long"])

    def permute(bucket: pa.Table) -> pa.Table:
        bucket = bucket.sort_by([(c, "ascending") for c in order])
        own = zlib.crc32(f"{seed}/{bucket['_group'][0]}/{bucket['_bucket'][0]}".encode())
        place = np.empty(bucket.num_rows, dtype=np.int64)
        place[fisher_yates(bucket.num_rows, own)] = np.arange(bucket.num_rows)
        return bucket.select([*names, "_group", "_bucket"]).append_column("_place", pa.array(place))

    placed = materialise(dealt.groupBy("_group", "_bucket").applyInArrow(permute, schema), "shuffled")
    counts = placed.groupBy("_group", "_bucket").agg(F.count("*").alias("_n"))
    inside = counts.withColumn("_before", F.sum("_n").over(Window.partitionBy("_group").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)))
    tops = {r["_group"]: r["n"] for r in counts.groupBy("_group").agg(F.sum("_n").alias("n")).collect()}  # GROUPS rows at most
    start, ahead = {}, 0
    for g in sorted(tops):
        start[g] = ahead
        ahead += tops[g]
    base = F.element_at(F.create_map(*(F.lit(x) for kv in start.items() for x in kv)), F.col("_group")) if start else F.lit(0)
    offsets = inside.select("_group", "_bucket", (base + F.coalesce("_before", F.lit(0))).alias("_start"))
    return placed.join(offsets, ["_group", "_bucket"]).withColumn("position", (F.col("_start") + F.col("_place")).cast("long")).select(*names, "position")


def shards(df: DataFrame, key: list[str], n: int = 16, **options) -> DataFrame:
    """shuffle(), dealt to n shards: columns shard and slot (gapless from 0 in each shard)."""
    dealt = shuffle(df.drop("shard", "slot"), key, **options)
    return dealt.withColumn("shard", (F.col("position") % n).cast("int")).withColumn("slot", F.floor(F.col("position") / n).cast("long")).drop("position")


def write_shards(df: DataFrame, path: str) -> None:
    """Write sharded rows in slot order, one folder a shard; several files a shard where it is large."""
    df.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def document_shards(docs: DataFrame, n: int = 16) -> DataFrame:
    """The rows of `docs` (doc_id, text), shuffled and dealt by the law `rows`, with digest columns."""
    text = F.coalesce(F.col("text"), F.lit(""))
    sized = docs.select("doc_id", "text", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    return shards(sized, ["doc_id", "text_crc32"], n, bucket_bytes=2 << 20).select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
