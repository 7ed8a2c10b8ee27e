"""Text files of sequences, one a line: integers, -1 closes an itemset, -2 the line.

``register(spark)`` adds the format ``seqtext``; ``parse_column`` reads the same lines with
built-in functions, for large files.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

SCHEMA = "sid long, itemsets array<array<string>>"


def parse_line(line: str) -> list[list[str]]:
    out, now = [], []
    for x in line.split():
        if x == "-2":
            break
        if x == "-1":
            out.append(sorted(set(now)))
            now = []
        else:
            now.append(x)
    return [*out, sorted(set(now))] if now else out


def parse_column(line: Column) -> Column:
    """The itemsets of a line."""
    body = F.element_at(F.split(line, r"(^|\s)-2(\s|$)"), 1)
    sets = F.transform(F.split(F.btrim(body), r"(^|\s+)-1(?=\s|$)"), lambda s: F.array_sort(F.array_distinct(F.filter(F.split(F.btrim(s), r"\s+"), lambda x: x != ""))))
    # what stands behind the last -1 counts only if it holds an item
    return F.when(F.size(F.element_at(sets, -1)) == 0, F.slice(sets, 1, F.size(sets) - 1)).otherwise(sets)


def format_column(itemsets: Column | str) -> Column:
    return F.concat(F.array_join(F.transform(itemsets, lambda s: F.concat_ws(" ", s, F.lit("-1"))), " "), F.lit(" -2"))


def read(spark: SparkSession, path: str) -> DataFrame:
    """sid, itemsets with built-in functions; sid is a hash of file and place, stable between runs."""
    rows = spark.read.text(path).where(F.trim("value") != "")
    return rows.select(F.monotonically_increasing_id().alias("sid"), parse_column(F.col("value")).alias("itemsets"))


def write(sequences: DataFrame, path: str) -> None:
    sequences.select(format_column("itemsets").alias("value")).write.text(path)


class Part(InputPartition):
    def __init__(self, path: str, number: int):
        super().__init__(number)
        self.path, self.number = path, number


class Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[Part]:
        import glob
        import os

        found = sorted(glob.glob(os.path.join(self.path, "part-*"))) if os.path.isdir(self.path) else [self.path]
        return [Part(p, i) for i, p in enumerate(found)]

    def read(self, partition: Part) -> Iterator[tuple]:
        with open(partition.path, encoding="utf-8") as f:
            for i, line in enumerate(f):
                if line.strip():
                    yield (partition.number << 40) + i, parse_line(line)


class Writer(DataSourceWriter):
    def __init__(self, path: str):
        self.path = path

    def write(self, rows: Iterator) -> WriterCommitMessage:
        import os
        import uuid

        os.makedirs(self.path, exist_ok=True)
        with open(os.path.join(self.path, f"part-{uuid.uuid4().hex}"), "w", encoding="utf-8") as f:
            for row in rows:
                f.write(" ".join(" ".join([*s, "-1"]) for s in row["itemsets"]) + " -2\n")
        return WriterCommitMessage()


class SequenceText(DataSource):
    """For files on a file system that every worker mounts; ``read`` and ``write`` go through Spark's own."""

    @classmethod
    def name(cls) -> str:
        return "seqtext"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> Reader:
        return Reader(self.options["path"].removeprefix("file://"))

    def writer(self, schema, overwrite: bool) -> Writer:
        return Writer(self.options["path"].removeprefix("file://"))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SequenceText)
