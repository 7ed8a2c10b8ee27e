"""What is done with mined patterns. They come as (pattern, support, tokens, ...)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.pattern import TOKENS, parse, precedes_column, stats, text_of
from ..functions.semantics import FREE, GROWTH, Constraints, Semantics
from ..plans.stage import written
from .growth import Options
from .matching import occurs, support


def from_texts(df: DataFrame, texts: list[str]) -> DataFrame:
    """tokens of pattern texts, as a table."""
    rows = [([(e.neg, list(e.items)) for e in parse(t).elements],) for t in texts]
    return df.sparkSession.createDataFrame(rows, f"tokens {TOKENS}").select(text_of("tokens").alias("pattern"), "tokens")


def merge_redundant(patterns: DataFrame, c: Constraints = FREE) -> DataFrame:
    """One of each pair ``x !b b y`` and ``x b !b y``, the second, if both are there. They are equal only without gaps."""
    if c != FREE:
        raise ValueError("with maxgap or maxspan these patterns differ")
    at = lambda t, i: F.get(t, i)
    # move each absence of exactly the next itemset behind that itemset, where no other absence stands
    def twin(t: Column) -> Column:
        moved = F.transform(t, lambda e, i: F.when(e["neg"] & (e["items"] == at(t, i + 1)["items"]) & ~F.coalesce(at(t, i + 2)["neg"], F.lit(True)), at(t, i + 1)).when(~e["neg"] & (i > 0) & F.coalesce(at(t, i - 1)["neg"], F.lit(False)) & (at(t, i - 1)["items"] == e["items"]) & ~F.coalesce(at(t, i + 1)["neg"], F.lit(True)), at(t, i - 1)).otherwise(e))
        return text_of(moved)

    by = Window.partitionBy("_key").orderBy(F.col("_moved").asc())
    rows = patterns.withColumn("_key", twin(F.col("tokens"))).withColumn("_moved", (F.col("_key") != F.col("pattern")).cast("int"))
    return rows.withColumn("_n", F.row_number().over(by)).where("_n = 1").drop("_key", "_moved", "_n")


def same_sids(sequences: DataFrame, patterns: list[str], sem: Semantics = GROWTH, c: Constraints = FREE) -> DataFrame:
    """pattern, class, members: patterns held by exactly the same sequences. The class is the least pattern text."""
    flags = F.array(*(F.when(occurs("itemsets", p, sem, c), F.lit(p)) for p in patterns))
    held = sequences.select("sid", F.explode(F.filter(flags, lambda x: x.isNotNull())).alias("pattern"))
    # two sums of mixed ids and a count stand for the set, so no list of ids is gathered
    mark = held.groupBy("pattern").agg(F.count("*").alias("n"), F.sum(F.xxhash64("sid").cast("decimal(38,0)")).alias("a"), F.sum(F.xxhash64(F.lit(1), "sid").cast("decimal(38,0)")).alias("b"))
    by = Window.partitionBy("n", "a", "b")
    return mark.select("pattern", F.min("pattern").over(by).alias("class"), F.count("*").over(by).alias("members"))


def _above(patterns: DataFrame) -> DataFrame:
    """Pairs of a pattern and a strictly larger one, met through the first item, which both share."""
    key = F.element_at(F.element_at("tokens", 1)["items"], 1)
    left = patterns.select(F.col("pattern").alias("p"), F.col("tokens").alias("pt"), F.col("support").alias("ps"), key.alias("k"))
    right = patterns.select(F.col("pattern").alias("q"), F.col("tokens").alias("qt"), F.col("support").alias("qs"), key.alias("_k"))
    return left.join(right, (F.col("k") == F.col("_k")) & (F.col("p") != F.col("q")) & (F.size("pt") <= F.size("qt"))).where(precedes_column(F.col("pt"), F.col("qt")))


def closed(patterns: DataFrame) -> DataFrame:
    """Patterns without a larger one of equal support."""
    beaten = _above(patterns).where("ps = qs").select(F.col("p").alias("pattern")).distinct()
    return patterns.join(beaten, "pattern", "left_anti")


def maximal(patterns: DataFrame) -> DataFrame:
    """Patterns without a larger frequent one."""
    return patterns.join(_above(patterns).select(F.col("p").alias("pattern")).distinct(), "pattern", "left_anti")


def topk(patterns: DataFrame, k: int, per: list[Column | str] | None = None) -> DataFrame:
    order = [F.col("support").desc(), F.col("pattern").asc()]
    if not per:
        return patterns.orderBy(*order).limit(k)
    return patterns.withColumn("_n", F.row_number().over(Window.partitionBy(*per).orderBy(*order))).where(F.col("_n") <= k).drop("_n")


def endpoints(patterns: DataFrame, first: str | None = None, last: str | None = None, holds: str | None = None) -> DataFrame:
    """Patterns that begin with, end with or hold an item."""
    if first is not None:
        patterns = patterns.where(F.array_contains(F.element_at("tokens", 1)["items"], first))
    if last is not None:
        patterns = patterns.where(F.array_contains(F.element_at("tokens", -1)["items"], last))
    if holds is not None:
        patterns = patterns.where(F.exists("tokens", lambda t: F.array_contains(t["items"], holds)))
    return patterns


def contrast(sequences: DataFrame, classes: DataFrame, patterns: list[str], sem: Semantics = GROWTH, c: Constraints = FREE) -> DataFrame:
    """pattern, in_class, out_class, growth_rate. classes: sid, class (0 or 1). The rate of shares is null where the other class lacks the pattern."""
    rows = sequences.join(classes, "sid")
    of = lambda k, p: F.coalesce(F.sum(F.when((F.col("class") == k) & occurs("itemsets", p, sem, c), 1).otherwise(0)), F.lit(0)).cast("long")
    sums = rows.agg(F.sum(F.when(F.col("class") == 1, 1).otherwise(0)).alias("n1"), F.sum(F.when(F.col("class") == 0, 1).otherwise(0)).alias("n0"), *(of(k, p).alias(f"s{k}_{i}") for i, p in enumerate(patterns) for k in (1, 0)))
    each = F.array(*(F.struct(F.lit(parse(p).text).alias("pattern"), F.col(f"s1_{i}").alias("in_class"), F.col(f"s0_{i}").alias("out_class")) for i, p in enumerate(patterns)))
    flat = sums.select("n1", "n0", F.explode(each).alias("r")).select("r.*", "n1", "n0")
    rate = (F.col("in_class") * F.col("n0")) / F.nullif(F.col("out_class") * F.col("n1"), F.lit(0))
    return flat.select("pattern", "in_class", "out_class", F.round(rate, 6).alias("growth_rate"))


def contrast_items(items: DataFrame, classes: DataFrame, patterns: list[str], maxgap: int | None = None) -> DataFrame:
    """contrast of (sid, pos, item) under total absence and soft occurrence: places of the patterns' items alone are kept, as bits, so long sequences cost little."""
    from . import bit_engine

    parsed = [parse(p) for p in patterns]
    names = sorted({x for p in parsed for e in p.elements for x in e.items})
    named = F.col("item").isin(names)
    # a cell without an item stands for all others, so that every sequence is counted
    word = F.when(named, F.expr("cast((pos - 1) div 64 as int)")).otherwise(0).alias("word")
    one = F.when(named, F.expr("shiftleft(1L, cast((pos - 1) % 64 as int))")).otherwise(F.lit(0).cast("long"))
    cells = items.groupBy("sid", F.when(named, F.col("item")).alias("item"), word).agg(F.bit_or(one).alias("bits"))
    rows = cells.groupBy("sid").agg((F.max("word") + 1).alias("words"), F.collect_list(F.struct("item", "word", "bits")).alias("cells"))
    rows = rows.join(classes.select("sid", F.col("class").cast("int").alias("class")), "sid").select("class", "words", "cells")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros((2, len(parsed) + 1), np.int64)
        for batch in batches:
            for k in (0, 1):
                part = batch.filter(pc.equal(batch.column(0), k)).select(["words", "cells"])
                for chunk in bit_engine.chunks(iter([part]), names, [], Options(maxgap=maxgap)):
                    out[k] += [chunk.masks.shape[2], *(np.count_nonzero(bit_engine.held(chunk, names, p)) for p in parsed)]
        k, i = np.indices(out.shape)
        yield pa.RecordBatch.from_arrays([pa.array(k.ravel().astype(np.int32)), pa.array(i.ravel().astype(np.int32) - 1), pa.array(out.ravel())], ["class", "i", "n"])

    of = lambda k: F.coalesce(F.sum(F.when(F.col("class") == k, F.col("n"))), F.lit(0)).cast("long")
    counts = written(rows.mapInArrow(run, "class int, i int, n long").groupBy("i").agg(of(1).alias("in_class"), of(0).alias("out_class")))
    whole = counts.where("i = -1").select(F.col("in_class").alias("n1"), F.col("out_class").alias("n0"))
    text = items.sparkSession.createDataFrame([(i, p.text) for i, p in enumerate(parsed)], "i int, pattern string")
    flat = F.broadcast(text).join(counts, "i", "left").na.fill(0, ["in_class", "out_class"]).join(F.broadcast(whole), how="left")
    rate = (F.col("in_class") * F.col("n0")) / F.nullif(F.col("out_class") * F.col("n1"), F.lit(0))
    return flat.select("pattern", "in_class", "out_class", F.round(rate, 6).alias("growth_rate"))


def switch(sequences: DataFrame, pairs: list[tuple[str, str]], c: Constraints = FREE) -> DataFrame:
    """For each pair (x, y): support of ``x x``, ``x y x`` and ``x !y x``."""
    from ..functions.pattern import build

    texts = [build(e).text for x, y in pairs for e in ([(False, [x]), (False, [x])], [(False, [x]), (False, [y]), (False, [x])], [(False, [x]), (True, [y]), (False, [x])])]
    return support(sequences, list(dict.fromkeys(texts)), GROWTH, c)


def by_size(patterns: DataFrame) -> DataFrame:
    s = stats("tokens")
    return patterns.groupBy(s["n_items"].alias("n_items"), s["n_neg"].alias("n_neg")).agg(F.count("*").alias("patterns"))
