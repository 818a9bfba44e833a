"""Edge and adjacency files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "src long, dst long"


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, sep: str = r"\s+", comment: str = "#") -> DataFrame:
    """Text lines of two identifiers; lines that start with ``comment`` and
    lines without two numbers are skipped."""
    parts = F.split(F.trim("value"), sep)
    lines = spark.read.text(path).where(~F.col("value").startswith(comment))
    pairs = lines.select(F.try_element_at(parts, F.lit(1)).try_cast("long").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("dst"))
    return pairs.where("src is not null and dst is not null")


def read_adjacency(spark: SparkSession, path: str, sep: str = r"\s+") -> DataFrame:
    """Text lines of a vertex and its neighbours, as edges."""
    parts = F.split(F.trim("value"), sep)
    rows = spark.read.text(path).select(F.get(parts, F.lit(0)).try_cast("long").alias("src"), F.explode(F.slice(parts, F.lit(2), F.size(parts))).alias("dst"))
    return rows.select("src", F.col("dst").try_cast("long").alias("dst")).where("src is not null and dst is not null")


def write_edge_list(edges: DataFrame, path: str) -> None:
    edges.select(F.concat_ws("\t", "src", "dst").alias("value")).write.text(path)


def write_adjacency(adjacency: DataFrame, path: str) -> None:
    """(id, neighbours) as text lines."""
    texts = F.transform("neighbours", lambda x: x.cast("string"))
    adjacency.select(F.concat_ws(" ", F.col("id").cast("string"), texts).alias("value")).write.text(path)


def read_edges(spark: SparkSession, path: str, format: str = "parquet") -> DataFrame:
    """Edges (src, dst) of any format Spark reads; csv files have a header."""
    reader = spark.read.format(format)
    if format in ("csv", "json"):
        reader = reader.schema(EDGE_SCHEMA)
    if format == "csv":
        reader = reader.option("header", True)
    return reader.load(path).select("src", "dst")


def stream_edges(spark: SparkSession, folder: str, files_per_trigger: int = 1, schema: str = EDGE_SCHEMA) -> DataFrame:
    """A folder of Parquet files of edges, as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
