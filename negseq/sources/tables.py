"""Event files in, pattern tables out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators.growth import described
from ..plans.stage import bucketed


def load_events(spark: SparkSession, path: str, schema: str, kind: str = "csv", **options) -> DataFrame:
    """CSV, JSON or Parquet events with an explicit schema; a bad row is null rather than a guess."""
    if kind == "parquet":
        return spark.read.schema(schema).parquet(path)
    return getattr(spark.read.schema(schema).options(**({"header": True} | options if kind == "csv" else options)), kind)(path)


def save_patterns(patterns: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Partitioned by the number of items."""
    patterns.write.mode(mode).partitionBy("n_items").parquet(path)


def load_patterns(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def save_items(items: DataFrame, buckets: int) -> DataFrame:
    """The item store in buckets of sequences."""
    return bucketed(items, "sid", ["sid", "pos"], buckets)


def tree_text(traced: DataFrame) -> str:
    """A search tree (pattern, parent_pattern, op, support) in the DOT language; on the driver, for small trees."""
    edge = lambda x: x.replace('"', '\\"')
    lines = []
    for r in traced.orderBy("pattern").collect():
        lines.append(f'  "{edge(r["pattern"])}" [label="{edge(r["pattern"])}\\n{r["support"]}"];')
        if r["parent_pattern"]:
            lines.append(f'  "{edge(r["parent_pattern"])}" -> "{edge(r["pattern"])}" [label="{r["op"]}"];')
    return "\n".join(["digraph search {", *lines, "}"])


__all__ = ["described", "load_events", "load_patterns", "save_items", "save_patterns", "tree_text"]
