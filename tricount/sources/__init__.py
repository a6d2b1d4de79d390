"""Readers and writers of tables, edge lists, adjacency text and edge streams. Schemas are given, never inferred."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def register_views(spark: SparkSession, folder: str, names: list[str] | None = None) -> None:
    """Temporary views of the given tables."""
    for name in names or TABLES:
        table(spark, folder, name).createOrReplaceTempView(name)


def edge_list(spark: SparkSession, path: str, sep: str = "\t", comment: str = "#") -> DataFrame:
    """src, dst of a text edge list; lines that start with ``comment`` are skipped, malformed lines are dropped."""
    return spark.read.csv(path, schema=EDGES, sep=sep, comment=comment, mode="DROPMALFORMED").where("src is not null and dst is not null")


def edges(spark: SparkSession, path: str, format: str = "parquet") -> DataFrame:
    """src, dst from parquet, orc or json."""
    return spark.read.format(format).schema(EDGES).load(path)


def adjacency_text(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """src, dst from lines "node neighbour neighbour ..."."""
    line = F.split(F.trim("value"), sep)
    rows = spark.read.text(path).where("trim(value) <> '' and not startswith(value, '#')").select(line[0].cast("long").alias("src"), F.explode_outer(F.slice(line, 2, F.size(line))).alias("dst"))
    return rows.select("src", F.col("dst").cast("long").alias("dst")).where("dst is not null")


def edge_stream(spark: SparkSession, path: str, schema: T.StructType = EDGES, files_per_batch: int = 1) -> DataFrame:
    """A stream of the parquet files that arrive in a folder."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def write_edges(df: DataFrame, path: str, format: str = "parquet", mode: str = "overwrite") -> None:
    df.select("src", "dst").write.format(format).mode(mode).save(path)


def write_partitions(df: DataFrame, path: str, part: str = "part", mode: str = "overwrite") -> None:
    """One folder per block, so that a job over few blocks reads only those."""
    df.write.partitionBy(part).mode(mode).parquet(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, key: str = "id", mode: str = "overwrite") -> None:
    """A table bucketed and sorted by id: joins on it need no shuffle."""
    df.write.bucketBy(buckets, key).sortBy(key).mode(mode).saveAsTable(name)
