"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

A source's target is its share by weight of all words, at most ``most`` times its own
words, the excess being shared again by weight among the others; in closed form, sources fill up
in the order of their limit per weight. A source first gives its whole words as often
as they fit (complete epochs). For the rest its documents are ordered by exponential
keys divided by their quality weights, and a prefix sum over their words stops at the
budget; of the last document only the words that still fit are taken.

The prefix sum is in two levels, over key ranges and inside each, so a hot source is
spread over many tasks. Keys come from hashes of id and text, so reruns agree.

Defined results: a null, empty or blank text has size 0 and gives nothing; a null source
is a source, the last; a source without words has target 0; repeated rows are
separate documents of equal key, ordered arbitrarily among themselves but equal in all
columns but ``taken``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

WORD = r"[^\x20\x09-\x0D]+"
JUNK = "#$%&*|<>{}[]@~^_=+\\"


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def quality(text: Column) -> Column:
    """Weight of a document from 0.1 to 1: the share of characters that are no mark-up or filler, squared."""
    clean = F.length(F.translate(text, JUNK, "")) / F.greatest(F.length(text), F.lit(1))
    return F.greatest(F.lit(0.1), F.coalesce(F.round(clean * clean, 6), F.lit(0.1)))


def targets(sizes: DataFrame, weights: tuple[float, ...], most: float) -> DataFrame:
    """source, source_size -> the same with target. A window over one row per source."""
    by = Window.orderBy(F.col("source").asc_nulls_last())
    ranked = sizes.withColumn("at", F.row_number().over(by) - 1)
    ranked = ranked.withColumn("weight", F.element_at(F.array(*map(F.lit, map(float, weights))), F.pmod("at", F.lit(len(weights))).cast("int") + 1))
    limit = F.col("source_size") * float(most)
    fill = Window.orderBy(limit / F.col("weight"), "at")
    rest = fill.rowsBetween(0, Window.unboundedFollowing)
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    total = Window.partitionBy(F.lit(1))
    level = (F.sum("source_size").over(total) - F.coalesce(F.sum(limit).over(before), F.lit(0.0))) / F.sum("weight").over(rest)
    filled = ranked.withColumn("level", level).withColumn("ratio", limit / F.col("weight"))
    # the first source whose limit is not reached sets the level for it and all after it
    final = F.min(F.when(F.col("ratio") >= F.col("level"), F.struct("ratio", "at", "level"))).over(total)["level"]
    return filled.select("source", "source_size", F.least(limit, F.coalesce(final, F.col("ratio")) * F.col("weight")).alias("target"))


def mix(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), most: float = 3.0, ranges: int = 256, weight: Column | None = None, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """doc_id, size, source_size, target, taken, and (epochs, part): whole copies and words of one more copy. ``weight``: quality of a document, over the columns of docs."""
    text = F.col(text_col)
    weight = quality(text) if weight is None else weight
    digest = F.xxhash64(F.col(id_col).cast("string"), text)
    # an exponential key's rank is that of a uniform one: 1 - exp(-key)
    uniform = (F.pmod(digest, F.lit(2**52)) + 0.5) / F.lit(float(2**52))
    key = -F.log(uniform) / F.greatest(F.coalesce(weight, F.lit(0.0)), F.lit(1e-9))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), n_words(text).alias("size"), key.alias("key"), digest.alias("digest"))
    rows = rows.withColumn("band", F.floor((1 - F.exp(-F.col("key") / 2)) * ranges).cast("int"))
    per_band = rows.groupBy("source", "band").agg(F.sum("size").alias("band_size"))
    sums = per_band.withColumn("band_before", F.coalesce(F.sum("band_size").over(Window.partitionBy("source").orderBy("band").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    sized = per_band.groupBy("source").agg(F.sum("band_size").alias("source_size"))
    goal = targets(sized, weights, most)
    known = sums.join(goal, sums["source"].eqNullSafe(goal["source"])).select(sums["source"].alias("_source"), F.col("band").alias("_band"), "band_before", "source_size", "target")
    inside = Window.partitionBy("source", "band").orderBy("key", "digest", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("inside", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    rows = rows.join(known, rows["source"].eqNullSafe(known["_source"]) & (rows["band"] == known["_band"]))
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    budget = F.round(F.col("target") - epochs * F.col("source_size")).cast("long")
    part = F.greatest(F.lit(0), F.least(F.col("size"), budget - F.col("band_before") - F.col("inside")))
    part = F.when(epochs >= int(most), F.lit(0)).otherwise(part).cast("long")
    return rows.select("doc_id", "source", "digest", "size", "source_size", F.col("target").cast("double").alias("target"), (epochs * F.col("size") + part).alias("taken"), epochs.alias("epochs"), part.alias("part"))
