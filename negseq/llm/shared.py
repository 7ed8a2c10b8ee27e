"""Tables in the folder that driver and executors share, and connected components."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder of the session. Only a local master may do without one: its driver and tasks share a temporary folder."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where:
        return where.rstrip("/")
    found = spark.sparkContext._jsc.sc().getCheckpointDir()
    if not found.isDefined():
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(f"file://{tempfile.mkdtemp(prefix='negseq-')}")
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
    return found.get()


def written(df: DataFrame, spark: SparkSession | None = None) -> DataFrame:
    """Cut the lineage: write to the shared folder and read again."""
    spark = spark or df.sparkSession
    path = f"{shared_dir(spark)}/negseq-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def null_last(column: Column) -> Column:
    return F.coalesce(column, F.lit(2**63 - 1))


def components(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """The smallest id that each node reaches.

    nodes: id; edges: a, b (any direction; both ends among the nodes). Returns id,
    component. Alternates large-star and small-star steps, whose rounds grow with the
    logarithm of the longest chain. Each round is written to the shared folder; no id
    is gathered in one place, and a hub's links shrink to one per neighbour before
    they are grouped.
    """
    spark = nodes.sparkSession
    links = written(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    before = None
    while True:
        both = links.select("u", "v").unionAll(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("x"), F.least("x", "m").alias("m"))
        large = both.where("v > u").join(least, F.col("u") == F.col("x")).select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = written(large.where("u <> v").distinct(), spark)
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down.withColumnRenamed("u", "x"), F.col("u") == F.col("x"))
        small = small.select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
        links = written(small.where("u <> v").distinct(), spark)
        now = links.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    label = links.groupBy("u").agg(F.min("v").alias("component"))
    return nodes.join(label, nodes["id"] == label["u"], "left").select("id", F.coalesce("component", "id").alias("component"))
