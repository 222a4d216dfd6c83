"""Helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Labels of rows with this remainder of crc32(doc_id as text) mod 5 are never learnt from.
HELD_OUT = 0


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share, one of its own for each application.

    It lies in spark.checkpoint.dir, or in the checkpoint folder set on the context. Where there is neither, a local
    session (tests) gets a temporary folder; on a cluster that's an error, as executors wouldn't see the driver's folder.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="nbrmatch-")
        spark.sparkContext.setCheckpointDir(found)
    return f"{found.rstrip('/')}/{spark.sparkContext.applicationId}"


def materialise(df: DataFrame, name: str, compression: str = "snappy") -> DataFrame:
    """Write df to the shared folder and read it back: lineage is cut and a lost executor costs nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", compression).parquet(path)
    found = spark.read.schema(df.schema).parquet(path)
    found._written = path
    return found


def discard(*written: DataFrame) -> None:
    """Delete what materialise() wrote. For tables that no result reads any more, such as a loop's earlier rounds."""
    for df in written:
        if path := df.__dict__.get("_written"):
            _delete(df.sparkSession, path)


def clean(spark: SparkSession) -> None:
    """Delete all that this application's operators wrote to the shared folder. Their lazy results can't be read after."""
    _delete(spark, shared_dir(spark))


def _delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def fresh(taken: list[str], *names: str) -> list[str]:
    """The names, each with as many underscores in front as it takes to be none of `taken` (case aside)."""
    seen = {c.lower() for c in taken}
    out = []
    for n in names:
        while n.lower() in seen:
            n = f"_{n}"
        seen.add(n.lower())
        out.append(n)
    return out


#: Most rows of a table of common keys, which is broadcast: a key is common if it has this share of all rows.
COMMON = 2048


def spread(rows: DataFrame, per_key: DataFrame, on: list[str], total: int) -> DataFrame:
    """rows joined with per_key (on, n, ...), whose n counts the rows of each key among `total` rows; both written tables.

    Keys with a share of 1 in COMMON or more would each fall to one task. There are COMMON of them at most, so hashes of
    them go into the plan, their part of per_key is broadcast and their rows stay where they are. The rest is an ordinary
    join. A key that shares the hash of a common one is treated as it is, on both sides alike.
    """
    key = F.xxhash64(*on)
    hashes = [r[0] for r in per_key.where(F.col("n") * COMMON >= total).select(key).collect()]
    if not hashes:
        return rows.join(per_key, on)
    common = key.isin(hashes)
    return rows.where(~common).join(per_key.where(~common), on).unionByName(rows.where(common).join(F.broadcast(per_key.where(common)), on))


def held_out(doc_id: str = "doc_id") -> Column:
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == HELD_OUT, F.lit(False))


def training_rows(docs: DataFrame, labelled: DataFrame, label: str, most: int, seed: int = 7) -> DataFrame:
    """At most `most` labelled, not held-out documents, chosen by a seeded hash of the id: (doc_id, text, label).

    The choice is made on the narrow label table; its ids (16 bytes each, `most` at most) are then broadcast.
    Several labels of one document: the largest counts. Rows without id, text or label are left out.
    """
    chosen = (
        labelled.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & ~held_out())
        .groupBy("doc_id").agg(F.max(label).cast("int").alias("label"))
        .orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(most)
    )
    return docs.select("doc_id", "text").where(F.col("text").isNotNull()).join(F.broadcast(chosen), "doc_id")


def worker_cache(key: object, make):
    """A value that lives as long as the Python worker: later tasks in it get the same one. Values of other operators go."""
    import sys
    import types

    kept = sys.modules.setdefault("_nbrmatch_worker", types.ModuleType("_nbrmatch_worker")).__dict__
    if key not in kept:
        release(key)
        kept[key] = make()
    return kept[key]


def release(key: object = None) -> None:
    """Drop what other operators have left in this Python worker: all but the values whose key has the same first part.

    What that frees goes back to the system, once for each change of operator: a worker lives on from stage to stage.
    """
    import sys
    import types

    kept = sys.modules.setdefault("_nbrmatch_worker", types.ModuleType("_nbrmatch_worker")).__dict__
    family = lambda k: k[0] if isinstance(k, tuple) else k
    own = family(key)
    for k in list(kept):
        if not (isinstance(k, str) and k.startswith("__")) and (key is None or family(k) != own):
            del kept[k]
    if kept.get("__owner__", "") != own:
        kept["__owner__"] = own
        _trim()


def _trim() -> None:
    import ctypes
    import gc

    import pyarrow

    gc.collect()
    pyarrow.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def without_gc(run):
    """Run a batch iterator without the cycle collector: memo tables make each of its passes long, and hold no cycles."""

    def quiet(batches):
        import gc

        gc.disable()
        try:
            yield from run(batches)
        finally:
            gc.enable()

    return quiet
