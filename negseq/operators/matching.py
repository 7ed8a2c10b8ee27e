"""Matching given patterns as columns over ``itemsets array<array<string>>``.

A pattern compiles to a fold: the states after a positive itemset are an array of
(start, position, tainted); the next itemset extends them. With no maxspan the start is
dropped, so there are at most two states per position. Everything stays in the JVM.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.pattern import Pattern, parse
from ..functions.semantics import FREE, GROWTH, Constraints, Semantics

#: Patterns counted in one scan; a longer list takes several.
PER_SCAN = 200


def _array(items: tuple[str, ...]) -> Column:
    return F.array(*map(F.lit, items))


def total_absent(q: Column, itemset: Column) -> Column:
    return ~F.coalesce(F.arrays_overlap(q, itemset), F.lit(False))


def partial_absent(q: Column, itemset: Column) -> Column:
    return F.size(F.array_except(q, itemset)) > 0


def window_ok(q: tuple[str, ...], window: Column, sem: Semantics) -> Column:
    if not q:
        return F.lit(True)
    absent = total_absent if sem.non_inclusion == "total" else partial_absent
    if sem.embedding == "strict":
        return absent(_array(q), F.flatten(window))
    return F.forall(window, lambda s: absent(_array(q), s))


def _places(itemsets: Column, items: tuple[str, ...]) -> Column:
    """Positions whose itemset holds all items."""
    at = F.when(F.size(itemsets) > 0, F.sequence(F.lit(1), F.size(itemsets))).otherwise(F.array().cast("array<int>"))
    return F.filter(at, lambda j: F.size(F.array_except(_array(items), F.get(itemsets, j - 1))) == 0)


def _let(value: Column, body) -> Column:
    """Evaluate value once for a body that uses it many times."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _step(states: Column, places: Column, itemsets: Column, q: tuple[str, ...], sem: Semantics, c: Constraints) -> Column:
    def reach(s: Column, j: Column) -> Column:
        ok = (s["pos"] < j) & (F.lit(True) if c.maxgap is None else j - s["pos"] <= c.maxgap)
        return ok if c.maxspan is None else ok & (j - s["start"] <= c.maxspan)

    def clean(s: Column, j: Column) -> Column:
        return window_ok(q, F.slice(itemsets, s["pos"] + 1, j - s["pos"] - 1), sem)

    def to(j: Column, before: Column) -> Column:
        if sem.occurrence == "soft":
            kept = F.filter(before, lambda s: F.when(reach(s, j), clean(s, j)).otherwise(False))
            return F.transform(kept, lambda s: F.struct(s["start"].alias("start"), j.alias("pos"), F.lit(False).alias("tainted")))
        kept = F.filter(before, lambda s: reach(s, j))
        return F.transform(kept, lambda s: F.struct(s["start"].alias("start"), j.alias("pos"), (s["tainted"] | ~clean(s, j)).alias("tainted")))

    return _let(states, lambda before: F.array_distinct(F.flatten(F.transform(places, lambda j: to(j, before)))))


def occurs(itemsets: Column | str, p: Pattern | str, sem: Semantics = GROWTH, c: Constraints = FREE) -> Column:
    """Whether a sequence holds the pattern; null itemsets count as an empty sequence."""
    p = parse(p) if isinstance(p, str) else p
    itemsets = F.col(itemsets) if isinstance(itemsets, str) else itemsets
    itemsets = F.coalesce(itemsets, F.array().cast("array<array<string>>"))
    start = (lambda j: j) if c.maxspan is not None else (lambda j: F.lit(0))
    states = F.transform(_places(itemsets, p.positives[0]), lambda j: F.struct(start(j).alias("start"), j.alias("pos"), F.lit(False).alias("tainted")))
    for items, q in zip(p.positives[1:], p.absences, strict=True):
        states = _step(states, _places(itemsets, items), itemsets, q, sem, c)
    found = F.size(states) > 0
    return found if sem.occurrence == "soft" else _let(states, lambda s: (F.size(s) > 0) & ~F.exists(s, lambda x: x["tainted"]))


def _extend(places: Column, c: Constraints):
    """One more position for each embedding so far."""

    def ok(e: Column, j: Column) -> Column:
        reach = F.element_at(e, -1) < j
        if c.maxgap is not None:
            reach &= j - F.element_at(e, -1) <= c.maxgap
        return reach if c.maxspan is None else reach & (j - F.element_at(e, 1) <= c.maxspan)

    return lambda before: F.flatten(F.transform(before, lambda e: F.transform(F.filter(places, lambda j: ok(e, j)), lambda j: F.concat(e, F.array(j)))))


def embeddings(sequences: DataFrame, p: Pattern | str, c: Constraints = FREE) -> DataFrame:
    """sid, e: all positions of the positive itemsets, a row each."""
    p = parse(p) if isinstance(p, str) else p
    sets = F.col("itemsets")
    found = F.transform(_places(sets, p.positives[0]), lambda j: F.array(j))
    for items in p.positives[1:]:
        places = _places(sets, items)

        found = _let(found, _extend(places, c))
    return sequences.select("sid", "itemsets", F.explode(found).alias("e")).drop("itemsets")


def negative_embeddings(sequences: DataFrame, p: Pattern | str, sem: Semantics = GROWTH, c: Constraints = FREE) -> DataFrame:
    """sid, e, ok, violated: each embedding of the positive part, its verdict and the first gap that is violated."""
    p = parse(p) if isinstance(p, str) else p
    rows = embeddings(sequences, p, c).join(sequences.select("sid", "itemsets"), "sid")
    e, sets = F.col("e"), F.col("itemsets")
    verdicts = [F.when(~window_ok(q, F.slice(sets, F.element_at(e, k + 1) + 1, F.element_at(e, k + 2) - F.element_at(e, k + 1) - 1), sem), F.lit(k + 1)) for k, q in enumerate(p.absences) if q]
    bad = F.coalesce(*verdicts) if verdicts else F.lit(None).cast("int")
    return rows.select("sid", "e", bad.isNull().alias("ok"), bad.alias("violated"))


def next_match(sequences: DataFrame, p: Pattern | str, after: Column | None = None, sem: Semantics = GROWTH, c: Constraints = FREE) -> DataFrame:
    """sid, e: the first embedding, in lexicographic order, that satisfies the absences (and comes after the given one)."""
    rows = negative_embeddings(sequences, p, sem, c).where("ok")
    if after is not None:
        rows = rows.where(F.col("e") > after)
    return rows.groupBy("sid").agg(F.min("e").alias("e"))


def supporting(sequences: DataFrame, p: Pattern | str, sem: Semantics = GROWTH, c: Constraints = FREE) -> DataFrame:
    p = parse(p) if isinstance(p, str) else p
    need = [F.exists("itemsets", lambda s, x=x: F.array_contains(s, x)) for x in sorted({i for items in p.positives for i in items})]
    return sequences.where(reduce(lambda a, b: a & b, need)).where(occurs("itemsets", p, sem, c)).select("sid")


def support(sequences: DataFrame, patterns: list[Pattern | str], sem: Semantics = GROWTH, c: Constraints = FREE) -> DataFrame:
    """pattern, support, rel_support in one scan (for each PER_SCAN patterns)."""
    parsed = [parse(p) if isinstance(p, str) else p for p in patterns]
    out = []
    for at in range(0, len(parsed), PER_SCAN):
        part = parsed[at : at + PER_SCAN]
        sums = sequences.agg(F.count("*").alias("n"), *(F.sum(F.when(occurs("itemsets", p, sem, c), 1).otherwise(0)).alias(f"s{i}") for i, p in enumerate(part)))
        rows = F.explode(F.array(*(F.struct(F.lit(p.text).alias("pattern"), F.coalesce(F.col(f"s{i}"), F.lit(0)).cast("long").alias("support")) for i, p in enumerate(part))))
        out.append(sums.select("n", rows.alias("r")).select("r.pattern", "r.support", F.round(F.coalesce(F.col("r.support") / F.nullif(F.col("n"), F.lit(0)), F.lit(0.0)), 6).alias("rel_support")))
    return reduce(DataFrame.unionAll, out)


def compare_semantics(sequences: DataFrame, patterns: list[Pattern | str], semantics: tuple[Semantics, ...], c: Constraints = FREE) -> DataFrame:
    """pattern, non_inclusion, embedding, occurrence, support: one scan for all."""
    cells = [(parse(p) if isinstance(p, str) else p, s) for p in patterns for s in semantics]
    sums = sequences.agg(*(F.sum(F.when(occurs("itemsets", p, s, c), 1).otherwise(0)).alias(f"s{i}") for i, (p, s) in enumerate(cells)))
    rows = F.array(*(F.struct(F.lit(p.text).alias("pattern"), F.lit(s.non_inclusion).alias("non_inclusion"), F.lit(s.embedding).alias("embedding"), F.lit(s.occurrence).alias("occurrence"), F.coalesce(F.col(f"s{i}"), F.lit(0)).cast("long").alias("support")) for i, (p, s) in enumerate(cells)))
    return sums.select(F.explode(rows).alias("r")).select("r.*")
