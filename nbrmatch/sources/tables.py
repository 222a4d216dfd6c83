"""Reading tables and edge lists, writing graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import LabeledGraph, build

EDGE_SCHEMA = "src long, dst long, elabel string"
VERTEX_SCHEMA = "vid long, vlabel string"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, separator: str = r"\s+", comment: str = "#") -> DataFrame:
    """Lines `src dst [label]` of text files; lines that don't start with two integers are left out."""
    line = F.trim("value")
    parts = F.split(line, separator, 3)
    rows = spark.read.text(path).where(~line.startswith(comment) & line.rlike(r"^-?\d+" + separator + r"-?\d+"))
    return rows.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"), F.when(F.size(parts) > 2, parts[2]).alias("elabel"))


def write_edge_list(edges: DataFrame, path: str) -> None:
    edges.select(F.concat_ws(" ", F.col("src").cast("string"), F.col("dst").cast("string"), "elabel").alias("value")).write.text(path)


def write_graph(g: LabeledGraph, path: str, kind: str = "parquet") -> None:
    """Vertices in folders by label, so that a label filter reads those alone; adjacency clustered by src."""
    g.vertices.repartition("vlabel").write.partitionBy("vlabel").format(kind).save(f"{path}/vertices")
    g.edges.repartitionByRange("src").sortWithinPartitions("src", "dst").write.format(kind).save(f"{path}/edges")


def read_graph(spark: SparkSession, path: str, kind: str = "parquet", directed: bool = False) -> LabeledGraph:
    return LabeledGraph(spark.read.schema(VERTEX_SCHEMA).format(kind).load(f"{path}/vertices").select("vid", "vlabel"), spark.read.schema(EDGE_SCHEMA).format(kind).load(f"{path}/edges"), directed)


def save_bucketed(adjacency: DataFrame, name: str, buckets: int) -> None:
    """Adjacency as a table bucketed and sorted by src: joins on src need no exchange."""
    adjacency.write.bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(name)


def in_memory(spark: SparkSession, vertices: list[tuple], edges: list[tuple], directed: bool = False, multi: bool = False) -> LabeledGraph:
    """A small literal graph. edges: (src, dst) or (src, dst, label)."""
    full = [(*e, None) if len(e) == 2 else tuple(e) for e in edges]
    return build(spark.createDataFrame(vertices, VERTEX_SCHEMA), spark.createDataFrame(full, EDGE_SCHEMA), directed, multi)
