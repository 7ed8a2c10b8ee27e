"""Random sequences with planted absence patterns.

Lengths are Poisson around the mean but long enough for a pattern, items are uniform, and everything
comes from hashes of (seed, sid, place), so partitioning does not matter and SQL can make
the same data. For at least the given share of sequences per pattern, an occurrence is planted: positives at
rising random places, and negated items in the windows between give way to others.
"""

from __future__ import annotations

import math
import random

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.pattern import Element, Pattern


def names(n_items: int) -> list[str]:
    return [f"i{k:0{len(str(n_items - 1))}d}" for k in range(n_items)]


def plan(n_items: int, n_patterns: int, pattern_len: int, seed: int) -> list[Pattern]:
    """Random patterns of about pattern_len items of which one, between two positives, is negated."""
    rng, out, alphabet = random.Random(seed), [], names(n_items)
    while len(out) < n_patterns:
        size = max(3, min(n_items, round(rng.gauss(pattern_len, 0.7))))
        items = rng.sample(alphabet, size)
        at = rng.randrange(1, size - 1)
        p = Pattern(tuple(Element(k == at, (x,)) for k, x in enumerate(items)))
        if p not in out:
            out.append(p)
    return out


def _u(seed: int, *parts: Column) -> Column:
    """Uniform in [0, 1): the first 32 bits of an MD5 digest."""
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), *(p.cast("string") for p in parts)))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") / F.lit(float(2**32))


def poisson_steps(mean: float) -> list[float]:
    """P(length <= k) for k from 0 until all but 1e-9 is reached; a length is the number of steps up to a uniform value."""
    out, term, k = [], math.exp(-mean), 0
    while not out or out[-1] < 1 - 1e-9:
        out.append(round((out[-1] if out else 0.0) + term, 12))
        k += 1
        term *= mean / k
    return out


def _planter(places: list[Column], positives: list[str], gaps: list, alphabet: list[str]):
    """The item at a place (from 0) once the pattern is planted."""

    def put(x: Column, i: Column) -> Column:
        out = x
        for j, q in enumerate(gaps):
            if q is not None:
                other = alphabet[(alphabet.index(q) + 1) % len(alphabet)]
                out = F.when((i + 1 > places[j]) & (i + 1 < places[j + 1]) & (x == q), F.lit(other)).otherwise(out)
        for j, item in enumerate(positives):
            out = F.when(i + 1 == places[j], F.lit(item)).otherwise(out)
        return out

    return put


def generate(spark: SparkSession, n: int = 500, mean_len: int = 20, n_items: int = 20, n_patterns: int = 3, pattern_len: int = 4, min_freq: float = 0.10, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """sequences (sid, len, itemsets) and truth (pattern, planted: number of sequences)."""
    patterns = plan(n_items, n_patterns, pattern_len, seed)
    longest = max(len(p.elements) for p in patterns) + 1
    steps = F.array(*map(F.lit, poisson_steps(mean_len)))
    rows = spark.range(n).withColumnRenamed("id", "sid").withColumn("_l", _u(seed, F.col("sid"), F.lit(0)))
    length = F.greatest(F.lit(longest), F.size(F.filter(steps, lambda x: x <= F.col("_l"))))
    alphabet = F.array(*map(F.lit, names(n_items)))
    rows = rows.withColumn("len", length)
    rows = rows.withColumn("items", F.transform(F.sequence(F.lit(1), F.col("len")), lambda i: F.get(alphabet, F.floor(_u(seed, F.col("sid"), i) * n_items).cast("int"))))
    truth = []
    for k, p in enumerate(patterns):
        planted = _u(seed + 7919 * (k + 1), F.col("sid")) < F.lit(min(1.0, 1.2 * min_freq))
        positives, m = [e.items[0] for e in p.elements if not e.neg], len([e for e in p.elements if not e.neg])
        # rising places: random offsets in equal parts of the sequence
        places = [(F.floor((F.lit(j) + _u(seed + k, F.col("sid"), F.lit(1000 + j)) * 0.999) * F.col("len") / m) + 1).cast("int") for j in range(m)]
        placed = F.col("items")
        gaps = [q[0] if q else None for q in p.absences]

        put = _planter(places, positives, gaps, names(n_items))
        rows = rows.withColumn("items", F.when(planted, F.transform(placed, put)).otherwise(placed)).withColumn(f"_p{k}", planted)
        truth.append(p.text)
    sequences = rows.select("sid", "len", F.transform("items", lambda x: F.array(x)).alias("itemsets"))
    table = rows.agg(*(F.sum(F.col(f"_p{k}").cast("int")).alias(f"n{k}") for k in range(len(patterns))))
    table = table.select(F.explode(F.array(*(F.struct(F.lit(t).alias("pattern"), F.col(f"n{k}").cast("long").alias("planted")) for k, t in enumerate(truth)))).alias("r")).select("r.*")
    return sequences, table
