"""What the engine asks of a Spark session."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Tables of more rows are never broadcast or handed to one task by this engine's own choice.
SMALL_ROWS = 200_000


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share, one of its own for each application.

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


def cut(df: DataFrame, name: str = "step", by: str | None = None) -> DataFrame:
    """Write df to the shared folder and read it back. Ends its lineage; survives lost executors.

    by: a column whose values get folders of their own, so that filters on it leave the other folders unread.
    """
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    writer = df.write if by is None else df.write.partitionBy(by)
    writer.parquet(path)
    found = df.sparkSession.read.schema(df.schema).parquet(path).select(*df.columns)
    found._written = path
    return found


def discard(*written: DataFrame | None) -> None:
    """Delete what cut() wrote. For tables that no result reads any more, such as a loop's earlier rounds."""
    for df in written:
        if df is not None and (path := df.__dict__.get("_written")):
            _files(df.sparkSession, path)[0].delete(_files(df.sparkSession, path)[1], True)


def written_bytes(df: DataFrame) -> int:
    """Bytes of the files that cut() wrote for df."""
    files, at = _files(df.sparkSession, df.__dict__["_written"])
    return files.getContentSummary(at).getLength()


def clean(spark: SparkSession) -> None:
    """Delete all that this application wrote to the shared folder. Lazy results that read it can't be read after."""
    files, at = _files(spark, shared_dir(spark))
    files.delete(at, True)


def _files(spark: SparkSession, path: str):
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()), at
