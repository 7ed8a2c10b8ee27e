"""Functions for SQL: patterns known only at run time."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.sequences import nested
from .pattern import parse
from .semantics import GROWTH, Constraints, embeddings, first_violation, occurs


def occurs_pattern(itemsets: pd.Series, pattern: pd.Series) -> pd.Series:
    """occurs_pattern(itemsets, 'a !c b'): an Arrow function; each text is parsed once a batch. Null in, null out."""
    known = {t: parse(t) for t in pattern.dropna().unique()}
    return pd.Series([None if s is None or p is None else occurs([[] if x is None else x for x in s], known[p]) for s, p in zip(itemsets, pattern, strict=True)], dtype="object")


def first_embedding(itemsets: pd.Series, pattern: pd.Series) -> pd.Series:
    """Positions of the first embedding that satisfies the absences, else null. Null in, null out."""
    known, out = {t: parse(t) for t in pattern.dropna().unique()}, []
    for s, t in zip(itemsets, pattern, strict=True):
        if s is None or t is None:
            out.append(None)
            continue
        sets = [[] if x is None else x for x in s]
        out.append(next((list(e) for e in embeddings(sets, known[t]) if first_violation(sets, known[t], e, GROWTH) is None), None))
    return pd.Series(out, dtype="object")


class SequenceEmbeddings:
    """sequence_embeddings(itemsets, pattern): a row per embedding of the positive part, its positions and whether the absences hold."""

    def eval(self, itemsets: list[list[str]], pattern: str):
        p = parse(pattern)
        for e in embeddings(itemsets, p, Constraints()):
            yield " ".join(map(str, e)), first_violation(itemsets, p, e, GROWTH) is None


def register(spark: SparkSession) -> None:
    spark.udf.register("occurs_pattern", F.pandas_udf(occurs_pattern, "boolean"))
    spark.udf.register("first_embedding", F.pandas_udf(first_embedding, "array<int>"))
    spark.udtf.register("sequence_embeddings", F.udtf(SequenceEmbeddings, returnType="positions: string, ok: boolean"))


def views(items: DataFrame, patterns: DataFrame | None = None) -> None:
    """Temporary views for SQL: seq_items (sid, pos, item), sequences (sid, len, itemsets) and, if given, patterns."""
    items.createOrReplaceTempView("seq_items")
    nested(items).createOrReplaceTempView("sequences")
    if patterns is not None:
        patterns.createOrReplaceTempView("patterns")
