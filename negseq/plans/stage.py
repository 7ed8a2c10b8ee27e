"""Where a lineage is cut and how an intermediate result is kept."""

from __future__ import annotations

import tempfile
import uuid

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession


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


def written(df: DataFrame) -> DataFrame:
    """Write to the shared folder and read again."""
    path = f"{shared_dir(df.sparkSession)}/level-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, by: str, sort: list[str], buckets: int) -> DataFrame:
    """Keep as a table in buckets, so that later joins and groups on ``by`` need no exchange."""
    name = f"negseq_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, by).sortBy(*sort).saveAsTable(name)
    return df.sparkSession.table(name)


def cached(df: DataFrame) -> DataFrame:
    """Cached with its partitioning; a lost part is computed again from its lineage."""
    return df.persist(StorageLevel.MEMORY_AND_DISK)
