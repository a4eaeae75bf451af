"""Reading tables and graphs, and layouts that keep a local method's reads local."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from attrgraph.operators.graph import EDGE_COLUMNS, Graph, from_edges


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A table of the star schema; only the named columns are read."""
    rows = spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")
    return rows.select(*columns) if columns else rows


def read(spark: SparkSession, path: str, format: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Any format of Spark's readers, with a schema where it has none of its own."""
    reader = spark.read.format(format).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def read_edge_list(spark: SparkSession, path: str, separator: str = r"\s+") -> Graph:
    """A text file of two ids (and perhaps a weight) a line; lines that begin with # or lack two numbers are left out."""
    parts = spark.read.text(path).where(~F.col("value").startswith("#")).select(F.split(F.trim("value"), separator).alias("p"))
    part = lambda i, kind: F.when(F.size("p") > i, F.element_at("p", i + 1)).try_cast(kind)
    return from_edges(parts.select(part(0, "long").alias("a"), part(1, "long").alias("b"), F.coalesce(part(2, "double"), F.lit(1.0)).alias("w")), weight="w")


def bucket_of(node: str, buckets: int):
    return F.pmod(F.hash(F.col(node)), F.lit(buckets))


def write_edges(g: Graph, path: str, buckets: int = 64) -> None:
    """Edges partitioned by ``src_bucket`` and sorted by src, so that a frontier's reads touch its buckets alone."""
    rows = g.edges.withColumn("src_bucket", bucket_of("src", buckets))
    rows.repartition(buckets, "src_bucket").sortWithinPartitions("src").write.partitionBy("src_bucket").parquet(path)


def read_edges(spark: SparkSession, path: str, buckets: list[int] | None = None) -> Graph:
    """The graph in a layout; with ``buckets``, only edges that start in those (their partitions alone are read)."""
    rows = spark.read.parquet(path)
    if buckets is not None:
        rows = rows.where(F.col("src_bucket").isin(sorted(buckets)))
    return Graph(rows.select(*EDGE_COLUMNS))


def write_factors(factors: DataFrame, path: str, buckets: int = 64) -> None:
    rows = factors.withColumn("bucket", bucket_of("node_id", buckets))
    rows.repartition(buckets, "bucket").sortWithinPartitions("node_id").write.partitionBy("bucket").parquet(path)


def read_factors(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).drop("bucket")


def write_clusters(clusters: DataFrame, path: str, format: str = "parquet", mode: str = "overwrite") -> None:
    clusters.write.format(format).mode(mode).save(path) if format != "noop" else clusters.write.format("noop").mode(mode).save()
