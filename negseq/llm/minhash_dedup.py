"""Near-duplicate groups by b-bit MinHash.

A document's set holds the hashes of its distinct ``shingle``-word runs. Documents of
equal sets form a class with one representative. Each representative keeps 160 minima:
32 bands of 5 generate candidates, the low 8 bits of all minima, packed in 20 longs,
estimate the similarity by bit counts, corrected for chance collisions, and what may
reach the threshold is confirmed on the full sets. Two sets at a similarity of 0.85
share no band with probability 7e-9 (0.8: 3e-6). As similar sets have similar sizes, a
bucket is a band's key and one of two neighbouring classes of size, which loses no pair.

Only components are wanted, so a bucket is not paired with itself. In each of a few rounds the bucket's
document of least hash is its hub and is compared with the others; a hub has then met
its whole bucket and leaves it. A bucket ends when what is left of it is of one
component. The documents of the buckets that stay open are then grouped anew, by their rarest
shingles, of which two linked ones must share one (an exact prefix bound); in such a group each
document outside the largest component meets those of other components, in parts of bounded size.
A pair goes on only at the first of its common rare shingles, if what lies behind it can be enough
and the packed signatures allow it.

What is lost: a pair of similarity s is missed if it shares no band, (1 - s^5)^32, or if its estimate
lies more than 5.5 standard deviations low (about 2e-8). Every other pair that shares a bucket is
compared, already connected, or under the threshold.

Defined results: a null, empty or blank text has an empty set and no link; fewer words
than a shingle make one shingle of the whole sequence; rows of one id are one node; a
row with a null id links with nothing and is kept (its component is null). Extra
columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce
from operator import add

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import words as W
from .shared import components, written

HASHES, BANDS, ROWS = 160, 32, 5
#: A pair whose estimate is so many standard deviations under the threshold is out.
DEVIATIONS = 5.5
#: Rounds of hubs before documents are grouped by their rarest shingles.
HUB_ROUNDS = 3
#: Rarest shingles that a row carries to tell the first common one, and documents outside the largest component that meet a group in one task.
CARRIED, PART = 16, 256

_rng = np.random.Generator(np.random.PCG64(77))
_FACTOR = _rng.integers(1, 2**63, HASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SHIFT = _rng.integers(1, 2**63, HASHES, dtype=np.uint64)


def sets(part: pa.RecordBatch, column: int, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of the slice's documents, one document after the other, and the number of each."""
    text = W.split(*W.utf8(part.column(column)))
    h = text.hashes(W.FOLD_CODE)
    words = np.diff(text.first)
    runs = W.rolling(h, shingle)
    same = text.doc[: len(runs)] == text.doc[shingle - 1 :] if len(runs) else np.zeros(0, bool)
    value, doc = [runs[same]], [text.doc[: len(runs)][same]]
    for n in range(1, shingle):
        short = np.flatnonzero(words == n)
        if len(short):
            total = np.full(len(short), n, np.uint64)
            for j in range(n):
                total = W.mix(total * W.BASE + h[text.first[short] + j])
            value.append(total)
            doc.append(short)
    value, doc = np.concatenate(value), np.concatenate(doc)
    order = np.lexsort((value, doc))
    value, doc = value[order], doc[order]
    if len(value):
        new = np.r_[True, (value[1:] != value[:-1]) | (doc[1:] != doc[:-1])]
        value, doc = value[new], doc[new]
    return value, np.bincount(doc, minlength=part.num_rows)


def sign(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in W.pieces(batches, "text"):
            value, n = sets(part, 1, shingle)
            full = np.flatnonzero(n)
            at = (np.cumsum(n) - n)[full]
            one, two = np.zeros(len(n), np.uint64), np.zeros(len(n), np.uint64)
            least = np.zeros((len(full), HASHES), np.uint64)
            if len(full):
                one[full] = np.add.reduceat(W.mix(value ^ W.BASE), at)
                two[full] = np.add.reduceat(W.mix(value + np.uint64(0x632BE59BD9B4E019)), at)
                for j in range(HASHES):
                    x = value * _FACTOR[j]
                    x += _SHIFT[j]
                    x ^= x >> np.uint64(32)
                    least[:, j] = np.minimum.reduceat(x, at)
            keys = np.zeros((len(full), BANDS), np.uint64)
            for b in range(BANDS):
                key = np.full(len(full), b + 1, np.uint64)
                for j in range(ROWS):
                    key = W.mix(key * W.BASE + least[:, b * ROWS + j])
                keys[:, b] = key
            low = np.ascontiguousarray(W.mix(least) & np.uint64(255)).astype(np.uint8).view(np.int64)
            has = np.isin(np.arange(len(n)), full)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array(n.astype(np.int64)), pa.array(W.signed(one)), pa.array(W.signed(two)), W.lists(pa.array(low.ravel()), has * low.shape[1]), W.lists(pa.array(W.signed(keys.ravel())), has * BANDS)],
                ["id", "n", "one", "two", "low", "keys"],
            )

    return run


def full_sets(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in W.pieces(batches, "text"):
            value, n = sets(part, 1, shingle)
            yield pa.RecordBatch.from_arrays([part.column(0), W.lists(pa.array(W.signed(value)), n)], ["id", "members"])

    return run


def estimate(a: Column | str, b: Column | str, bits: int = 8) -> Column:
    """Similarity of two packed signatures: lanes whose bits all agree, counted with bit_count and corrected for the chance of a random agreement."""

    def unequal(i: int) -> Column:
        v = F.get(a, F.lit(i)).bitwiseXOR(F.get(b, F.lit(i)))
        for shift in (4, 2, 1):
            v = v.bitwiseOR(F.shiftrightunsigned(v, shift))
        return F.bit_count(v.bitwiseAND(F.lit(0x0101010101010101)))

    # one expression for each long, which compiles where a fold over the arrays does not
    differ = reduce(add, [unequal(i) for i in range(HASHES // 8)])
    chance = 2.0**-bits
    return F.greatest(F.lit(0.0), (1 - differ / F.lit(float(HASHES)) - chance) / (1 - chance))


def rare_shingles(full: DataFrame, ids: DataFrame, percent: int) -> DataFrame:
    """Of each document of ids the shingles of which two linked ones share one at least: bucket, id, place, begin (the first of them, in order).

    Shingles are ordered by how many of these documents hold them. A document of n shingles
    and a linked one share at least percent of n, so one of the first n - percent of n + 1.
    Those that no other document holds come first and make no row. place counts from one.
    """
    held = full.join(ids.select("id"), "id", "left_semi").select("id", F.size("members").alias("n"), F.explode("members").alias("bucket"))
    often = held.groupBy("bucket").agg(F.count("*").alias("docs")).where("docs > 1")
    of_doc = Window.partitionBy("id")
    at = F.row_number().over(of_doc.orderBy("docs", "bucket"))
    ranked = held.join(often, "bucket").select("id", "n", "bucket", at.alias("at"), (at + F.col("n") - F.count("*").over(of_doc)).alias("place"))
    ranked = ranked.where(f"place <= n - (({percent} * n + 99) div 100) + 1")
    begin = F.transform(F.array_sort(F.collect_list(F.when(F.col("at") <= CARRIED, F.struct("at", "bucket")))), lambda x: x["bucket"])
    return ranked.join(ranked.groupBy("id").agg(begin.alias("begin")), "id").select("bucket", "id", "place", "begin")


def in_main(rows: DataFrame) -> DataFrame:
    """Rows of buckets of more than one component, with the largest one as main and the number of parts for the others."""
    kinds = rows.groupBy("bucket", "component").agg(F.count("*").alias("size"))
    most = kinds.groupBy("bucket").agg(F.max_by("component", F.struct("size", "component")).alias("main"), F.count("*").alias("kinds"), F.ceil((F.sum("size") - F.max("size")) / PART).cast("int").alias("parts")).where("kinds > 1")
    return rows.join(most.select("bucket", "main", "parts"), "bucket")


def near_links(signed: DataFrame, text: DataFrame, shingle: int, percent: int) -> DataFrame:
    """Links a, b that connect each component of the representatives."""
    spark = signed.sparkSession
    # sizes of a linked pair differ by a factor of 100 / percent at most, so their classes by one at most
    size_class = F.floor(F.log(F.col("n").cast("double")) / F.lit(math.log(100 / percent) * (1 + 1e-9))).cast("long")
    each = signed.select("id", "n", F.explode("keys").alias("key"), size_class.alias("class"))
    # a document is in the bucket of its class and, as a guest, in that of the next one
    own = F.struct(F.xxhash64("key", "class").alias("bucket"), F.lit(False).alias("guest"))
    next_ = F.struct(F.xxhash64("key", F.col("class") + 1).alias("bucket"), F.lit(True).alias("guest"))
    each = each.select("id", "n", F.explode(F.array(own, next_)).alias("at")).select("id", "n", "at.bucket", "at.guest")
    # guests alone meet in the bucket of their own class
    size = each.groupBy("bucket").agg(F.count("*").alias("members"), F.min("guest").alias("guests")).where("members > 1 and not guests")
    left = written(each.join(size, "bucket").select("bucket", "id", "n"), spark)
    wanted = left.select("id").distinct()
    full = written(text.join(wanted, "id").select("id", "text").mapInArrow(full_sets(shingle), "id long, members array<long>").dropDuplicates(["id"]), spark)
    low = written(signed.join(wanted, "id").select("id", "n", "low"), spark)
    least = percent / 100 - DEVIATIONS * math.sqrt(percent / 100 * (1 - percent / 100) / HASHES)
    fits = f"100 * n_a >= {percent} * n_b and 100 * n_b >= {percent} * n_a"
    likely_ = estimate("low_a", "low_b") >= least

    def confirmed(likely: DataFrame) -> DataFrame:
        member = lambda k: full.select(F.col("id").alias(k), F.col("members").alias(f"of_{k}"))
        both = likely.join(member("a"), "a").join(member("b"), "b")
        common = F.size(F.array_intersect("of_a", "of_b"))
        found = both.select("a", "b", common.alias("common"), (F.size("of_a") + F.size("of_b")).alias("sizes"))
        return written(found.where(f"100 * common >= {percent} * (sizes - common)").select("a", "b"), spark)

    edges, component = None, None
    for first in [*[True] * HUB_ROUNDS, False]:
        now = left.withColumn("component", F.col("id")) if component is None else left.join(component, "id", "left").withColumn("component", F.coalesce("component", "id"))
        if first:
            at = F.xxhash64("id")
            open_ = now.groupBy("bucket").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.min(at).alias("lead")).where("low <> high")
            now = written(now.join(open_.select("bucket", "lead"), "bucket"), spark)
        else:
            kinds = now.groupBy("bucket").agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low <> high")
            still = written(now.join(kinds, "bucket", "left_semi").select("id", "component").distinct(), spark)
            now = written(in_main(rare_shingles(full, still, percent).join(still, "id")).join(low, "id"), spark)
        if now.isEmpty():
            break
        if first:
            chosen = now.where(at == F.col("lead")).select("bucket", F.col("id").alias("hub"), F.col("n").alias("n_hub"), F.col("component").alias("c"))
            pairs = now.join(chosen, "bucket").where("component <> c").where(f"100 * n >= {percent} * n_hub and 100 * n_hub >= {percent} * n").select(F.least("id", "hub").alias("a"), F.greatest("id", "hub").alias("b")).distinct()
            sig = lambda k: low.select(F.col("id").alias(k), F.col("low").alias(f"low_{k}"))
            likely = pairs.join(sig("a"), "a").join(sig("b"), "b").where(likely_).select("a", "b")
            left = now.select("bucket", "id", "n").join(chosen.select("bucket", F.col("hub").alias("id")), ["bucket", "id"], "left_anti")
        else:
            side = lambda k: now.select("bucket", "main", "parts", *[F.col(c).alias(f"{c}_{k}") for c in ("id", "component", "n", "low", "place", "begin")])
            outside = side("a").where("component_a <> main").withColumn("part", F.pmod(F.xxhash64("id_a"), F.col("parts")).cast("int")).drop("main", "parts")
            others = side("b").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
            once = "component_a <> component_b and (component_b = main or id_a < id_b)"
            # nothing before their first common shingle is common, and at most what is behind it
            bounded = f"{100 + percent} * (1 + least(n_a - place_a, n_b - place_b)) >= {percent} * (n_a + n_b)"
            both = F.array_intersect("begin_a", "begin_b")
            here = (F.size(both) == 0) | (F.get(both, F.lit(0)) == F.col("bucket"))
            likely = outside.join(others, ["bucket", "part"]).where(once).where(fits).where(bounded).where(likely_).where(here).select(F.least("id_a", "id_b").alias("a"), F.greatest("id_a", "id_b").alias("b")).distinct()
        found = confirmed(likely)
        edges = found if edges is None else edges.unionAll(found)
        if not found.isEmpty():
            nodes = edges.select(F.explode(F.array("a", "b")).alias("id")).distinct()
            component = written(components(nodes, edges), spark)
    return component if component is not None else spark.createDataFrame([], "id long, component long")


def minhash_dedup(docs: DataFrame, shingle: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: id, n_shingles, component_id, kept."""
    spark = docs.sparkSession
    text = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    signed = written(text.mapInArrow(sign(shingle), "id long, n long, one long, two long, low array<long>, keys array<long>"), spark)
    # rows of one id are one node, so a class is joined by its least id and by shared ids
    classes = signed.where("n > 0 and id is not null").groupBy("one", "two", "n").agg(F.min("id").alias("lead"))
    lead = written(classes, spark)
    ids = signed.where("n > 0 and id is not null").select("id", "one", "two", "n").join(lead, ["one", "two", "n"]).select("id", "lead")
    first = signed.join(lead.select("one", "two", "n", F.col("lead").alias("id")), ["one", "two", "n", "id"], "left_semi").dropDuplicates(["one", "two", "n", "id"])
    near = near_links(first, text, shingle, percent)
    named = ids.distinct().join(near.select(F.col("id").alias("lead"), "component"), "lead", "left").select("id", F.coalesce("component", "lead").alias("component"))
    repeated = written(named.groupBy("id").agg(F.min("component").alias("component"), F.max("component").alias("other")), spark)
    more = repeated.where("component <> other").select(F.col("component").alias("a"), F.col("other").alias("b"))
    if not more.isEmpty():
        seen = named.select(F.col("id").alias("a"), F.col("component").alias("b")).where("a <> b")
        repeated = components(named.select("id").distinct(), seen)
    out = signed.select("id", "n").join(repeated.select("id", "component"), "id", "left")
    component = F.coalesce("component", "id")
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(component == F.col("id"), F.lit(True)).alias("kept"))
