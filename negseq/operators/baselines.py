"""What the growth miner is held against.

Positive prefix growth; the library's PrefixSpan; the partner miner, which gets the support
of an absence pattern by set algebra on the sequence ids of positive patterns; level-wise
generate and test under the semantics of two older methods; and exhaustive search.
"""

from __future__ import annotations

from itertools import combinations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.pattern import TOKENS, Element, Pattern, parse, positive_part, stats, text_of
from ..functions.semantics import FREE, GROWTH, Constraints, Semantics, occurs
from ..plans.planner import BROADCAST_ROWS, LOCAL_ROWS, small
from ..plans.stage import written as cached
from .growth import Options, described, frequent_items, mine, n_sequences, size_of, threshold, with_sids


def mine_positive(items: DataFrame, sigma, options: Options | None = None) -> DataFrame:
    from dataclasses import replace

    return mine(items, sigma, replace(options or Options(), negatives=False))


def mine_positive_library(sequences: DataFrame, sigma, max_items: int = 3) -> DataFrame:
    """pattern, support from PrefixSpan of the ML library; no constraints."""
    from pyspark.ml.fpm import PrefixSpan

    n = sequences.count()
    minsup = max(1, threshold(n, sigma))
    kept = sequences.select(F.filter("itemsets", lambda s: F.size(s) > 0).alias("sequence"))
    # a share slightly under the count, as the library rounds up
    found = PrefixSpan(minSupport=(minsup - 0.5) / n, maxPatternLength=max_items).findFrequentSequentialPatterns(kept)
    tokens = F.transform("sequence", lambda s: F.struct(F.lit(False).alias("neg"), F.array_sort(s).alias("items")))
    return found.select(text_of(tokens.cast(TOKENS)).alias("pattern"), F.col("freq").cast("long").alias("support")).where(F.col("support") >= minsup)


def _masks(tokens: Column) -> Column:
    """Sets of inner elements without two neighbours, as bits."""
    inner = F.size(tokens) - 2
    every = F.when(inner > 0, F.sequence(F.lit(1), F.pow(F.lit(2), inner).cast("int") - 1)).otherwise(F.array().cast("array<int>"))
    return F.filter(every, lambda m: m.bitwiseAND(F.shiftright(m, 1)) == 0)


def _bit(mask: Column, i: Column) -> Column:
    """Whether element i (from 0) of a pattern is negated."""
    return (i > 0) & (F.call_function("shiftright", mask, F.greatest(i - 1, F.lit(0))).bitwiseAND(F.lit(1)) == 1)


def partner_candidates(positives: DataFrame, max_neg_size: int | None = 1, unit: str = "itemset") -> DataFrame:
    """tokens, pattern, positive, partners: every way to negate inner, not adjacent elements of a positive pattern. Partners are the positive part with one negated element present."""
    rows = positives.select(F.col("tokens").alias("of"), F.explode(_masks(F.col("tokens"))).alias("mask"))
    rows = rows.select(F.transform("of", lambda t, i: F.struct(_bit(F.col("mask"), i).alias("neg"), t["items"].alias("items"))).cast(TOKENS).alias("tokens"))
    if max_neg_size is not None:
        rows = rows.where(stats("tokens")["max_neg_size"] <= max_neg_size)
    def present(items) -> Column:
        """One partner for each negated element and each of its units."""
        def one(k: Column, unit_items: Column) -> Column:
            kept = F.filter("tokens", lambda t, i: ~t["neg"] | (i == k))
            return text_of(F.transform(F.transform(kept, lambda t: F.struct(F.lit(False).alias("neg"), F.when(t["neg"], unit_items).otherwise(t["items"]).alias("items"))), lambda t: t))

        at = F.filter(F.transform("tokens", lambda t, i: F.struct(t["neg"].alias("neg"), t["items"].alias("items"), i.alias("k"))), lambda t: t["neg"])
        if items == "itemset":
            return F.transform(at, lambda t: one(t["k"], t["items"]))
        return F.flatten(F.transform(at, lambda t: F.transform(t["items"], lambda x: one(t["k"], F.array(x)))))

    return rows.select("tokens", text_of("tokens").alias("pattern"), text_of(positive_part("tokens")).alias("positive"), present(unit).alias("partners")).dropDuplicates(["pattern"])


def partner_thresholds(n: int, sigma, partner_ratio: float) -> tuple[int, int]:
    """Least support of a pattern and of its partner, of n sequences."""
    minsup = max(1, threshold(n, sigma))
    # exact ceiling of the scaled threshold
    return minsup, max(1, -((-minsup * round(partner_ratio * 1000)) // 1000))


def mine_partner(items: DataFrame, sigma, partner_ratio: float = 0.7, max_items: int = 3, max_neg_size: int | None = 1, unit: str = "itemset", maxgap: int | None = None, maxspan: int | None = None, boundary: bool = False, engine: str = "auto", packed=None) -> DataFrame:
    """pattern, support, n_items, n_pos, n_neg, tokens. Strict occurrence; a pattern is found only if its positive partner is frequent at partner_ratio times the threshold. boundary: also patterns of a lone item and its absence (`!x`), with the sequences that lack it. engine: 'frontier', 'bits', or 'auto', which mines a database of at most LOCAL_ROWS events root by root in tasks that share it, and a larger one on bits. packed: as for mine."""
    from . import bit_engine
    from .local_engine import mine_partner_small

    if maxgap is not None or maxspan is not None:
        raise ValueError("set algebra on sequence ids cannot express maxgap or maxspan")
    packed = bit_engine.pack(items) if packed is None and engine != "frontier" else packed
    n, rows = size_of(items) if packed is None else (packed.n, packed.events)
    minsup, low = partner_thresholds(n, sigma, partner_ratio)
    if engine == "auto" and rows <= LOCAL_ROWS and not boundary:
        return described(mine_partner_small(items, minsup, low, max_items, max_neg_size, unit))
    # up to four items leave room for one negated element, whose single partner's support says how many sequences are lost
    single = max_items is not None and max_items <= 4 and (unit == "itemset" or max_neg_size == 1)
    on_bits = single and engine != "frontier" and (engine == "bits" or rows > LOCAL_ROWS) and bit_engine.fits(packed, min(low, minsup))
    if engine == "bits" and not on_bits:
        raise ValueError("several partners or a long sequence need the ids of sequences")
    positive = Options(max_items=max_items, negatives=False)
    if on_bits:
        counted = cached(described(bit_engine.mine_packed(packed, min(low, minsup), positive)).select("pattern", "support", "tokens"))
    else:
        lists = cached(with_sids(items, min(low, minsup), positive))
        counted = lists.groupBy("pattern").agg(F.count("*").alias("support"), F.first("tokens").alias("tokens"))
    found = described(counted.where(F.col("support") >= minsup))
    candidates = cached(partner_candidates(counted.where(F.col("support") >= low), max_neg_size, unit))
    by_partner = candidates.select(F.col("pattern").alias("candidate"), F.explode(F.array_distinct("partners")).alias("pattern"))
    # a partner holds the positive part, so its sequences are among those of the positive part
    if on_bits:
        lost = by_partner.join(counted.select("pattern", F.col("support").alias("lost")), "pattern").select("candidate", "lost")
    else:
        lost = by_partner.join(lists.select("pattern", "sid"), "pattern").select("candidate", "sid").distinct().groupBy("candidate").agg(F.count("*").alias("lost"))
    whole = candidates.join(counted.select(F.col("pattern").alias("positive"), "support"), "positive").join(lost, F.col("pattern") == F.col("candidate"), "left")
    negative = whole.withColumn("support", F.col("support") - F.coalesce("lost", F.lit(0))).where(F.col("support") >= minsup)
    out = found.unionByName(described(negative.select("tokens", "support")))
    if boundary:
        lone = counted.where(F.size("tokens") == 1).where(F.lit(n) - F.col("support") >= minsup)
        lone = lone.select(F.concat(F.lit("!"), F.col("pattern")).alias("pattern"), (F.lit(n) - F.col("support")).alias("support"), stats("tokens")["n_items"].alias("n_items"), F.lit(0).alias("n_pos"), F.lit(1).alias("n_neg"), "tokens")
        out = out.unionByName(lone)
    return out


def _places(items: DataFrame, able: DataFrame) -> DataFrame:
    """pattern, npos, k, sid, pos: where the k-th positive itemset of each pattern stands."""
    each = able.select("pattern", F.size("tokens").alias("npos"), F.posexplode("tokens").alias("k", "t")).select("pattern", "npos", "k", F.size("t.items").alias("size"), F.explode("t.items").alias("item"))
    return items.join(each, "item").groupBy("pattern", "npos", "k", "sid", "pos").agg(F.count("*").alias("n"), F.first("size").alias("size")).where("n = size").drop("n", "size")


def _windows(places: DataFrame, top: int, maxgap: int | None) -> DataFrame:
    """pattern, sid, gap, a, b: the windows of each gap in any embedding that keeps maxgap. A place is live from the left if the pattern up to it ends there, from the right if the rest begins there; a window joins two live places. Without maxgap, only the widest window of each gap."""
    key = ["pattern", "sid"]
    step = lambda k: places.where(F.col("k") == k)

    def live(order: range, back: bool) -> list[DataFrame]:
        out = []
        for k in order:
            now = step(k) if not back else step(k).where("npos > k")
            first = F.col("k") == (0 if not back else F.col("npos") - 1)
            rows = now.where(first).select(*key, "npos", "pos")
            if out:
                far = F.col("_p") - F.col("pos") if back else F.col("pos") - F.col("_p")
                near = (far > 0) if maxgap is None else (far > 0) & (far <= maxgap)
                rows = rows.unionAll(now.where(~first).join(out[-1].select(*key, F.col("pos").alias("_p")), key).where(near).select(*key, "npos", "pos").distinct())
            if maxgap is None:
                # the least beginning, or the greatest end, lets the most follow
                rows = rows.groupBy(*key, "npos").agg((F.max if back else F.min)("pos").alias("pos"))
            out.append(cached(rows))
        return out

    left, right = live(range(top - 1), False), live(range(top - 1, 0, -1), True)[::-1]
    out = None
    for k in range(top - 1):
        far = F.col("b") - F.col("a")
        one = left[k].where(F.col("npos") > k + 1).select(*key, F.lit(k).alias("gap"), F.col("pos").alias("a")).join(right[k].select(*key, F.col("pos").alias("b")), key).where((far > 1) if maxgap is None else (far > 1) & (far <= maxgap))
        out = one if out is None else out.unionAll(one)
    return out


def _windows_by_embedding(places: DataFrame, top: int, o: Options) -> DataFrame:
    """The same with maxspan, which ties the first place to the last: every embedding is enumerated."""
    rows, done = places.where("k = 0").select("pattern", "npos", "sid", F.array("pos").alias("e")), None
    for k in range(1, top):
        ok = (F.col("pos") > F.element_at("e", -1)) & (F.lit(True) if o.maxgap is None else F.col("pos") - F.element_at("e", -1) <= o.maxgap) & (F.col("pos") - F.element_at("e", 1) <= o.maxspan)
        rows = rows.where(F.col("npos") > k).join(places.where(F.col("k") == k).select("pattern", "sid", "pos"), ["pattern", "sid"]).where(ok).select("pattern", "npos", "sid", F.concat("e", F.array("pos")).alias("e"))
        full = rows.where(F.col("npos") == k + 1)
        done = full if done is None else done.unionAll(full)
    pairs = F.transform(F.sequence(F.lit(1), F.size("e") - 1), lambda i: F.struct(F.get("e", i - 1).alias("a"), F.get("e", i).alias("b")))
    return done.select("pattern", "sid", F.posexplode(pairs).alias("gap", "w")).select("pattern", "sid", "gap", "w.a", "w.b").distinct()


def mine_strict(items: DataFrame, sigma, options: Options | None = None) -> DataFrame:
    """Strict occurrence with gap constraints: every constrained embedding of the positive part must lack the absences.

    A sequence violates (gap, item) if any embedding of a positive pattern has the item in that gap. A pattern with several
    absences is held by the holders of its positive part less the violators of any of them, so absences of one
    positive pattern grow by unions of violators, from those that are frequent alone.
    """
    from dataclasses import replace

    o = options or Options()
    n = n_sequences(items)
    minsup = max(1, threshold(n, sigma))
    positive = mine(items, minsup, replace(o, negatives=False), sequences=n)
    most = o.max_items if o.max_items is not None else 10**6
    able = cached(positive.where("n_pos >= 2").where(F.col("n_items") < most))
    top = able.agg(F.max("n_pos")).first()[0]
    if not o.negatives or top is None:
        return positive
    places = cached(_places(items, able))
    windows = _windows(places, top, o.maxgap) if o.maxspan is None else _windows_by_embedding(places, top, o)
    words = cached(frequent_items(items, minsup).select(F.col("item").alias("q")))
    inside = items.select("sid", "pos", F.col("item").alias("q")).join(small(words, n_words := words.count()), "q", "left_semi")
    bad = cached(windows.join(inside, "sid").where("pos > a and pos < b").select("pattern", "sid", "gap", "q").distinct())
    gone = bad.groupBy("pattern", "gap", "q").agg(F.count("*").alias("lost"))
    each = able.select("pattern", "tokens", "support", "n_items", F.explode(F.sequence(F.lit(0), F.col("n_pos") - 2)).alias("gap")).crossJoin(small(words, n_words))
    one = each.join(gone, ["pattern", "gap", "q"], "left").withColumn("support", F.col("support") - F.coalesce("lost", F.lit(0))).where(F.col("support") >= minsup)
    single = cached(one.select("pattern", "tokens", "n_items", "gap", "q", "support", F.xxhash64("pattern", "gap", "q").alias("id"), F.array(F.struct("gap", "q")).alias("absent")))
    lost = cached(single.select("id", "pattern", "gap", "q").join(bad, ["pattern", "gap", "q"]).select("id", "sid"))
    levels = [single]
    while not levels[-1].isEmpty():
        size = len(levels) + 1
        last = F.element_at("absent", -1)
        held = F.size(F.filter("absent", lambda x: x["gap"] == F.col("_gap")))
        room = F.lit(True) if o.max_neg_size is None else held < o.max_neg_size
        with_ = single.select(F.col("pattern").alias("_pattern"), F.col("gap").alias("_gap"), F.col("q").alias("_q"))
        pairs = levels[-1].where(F.col("n_items") + size <= most).join(with_, (F.col("pattern") == F.col("_pattern")) & (F.struct("_gap", "_q") > last)).where(room)
        child = pairs.select("pattern", "tokens", "n_items", F.col("_gap").alias("gap"), F.col("_q").alias("q"), "support", F.xxhash64("id", "_gap", "_q").alias("id"), F.concat("absent", F.array(F.struct(F.col("_gap").alias("gap"), F.col("_q").alias("q")))).alias("absent"), F.col("id").alias("parent"))
        more = cached(child.select("id", "parent", "pattern", "gap", "q").join(bad, ["pattern", "gap", "q"]).join(lost.withColumnRenamed("id", "parent"), ["parent", "sid"], "left_anti").select("id", "sid"))
        child = child.join(more.groupBy("id").agg(F.count("*").alias("lost")), "id", "left").withColumn("support", F.col("support") - F.coalesce("lost", F.lit(0))).where(F.col("support") >= minsup)
        child = cached(child.select(*single.columns, "parent"))
        lost = cached(more.join(child, "id", "left_semi").unionAll(child.select("id", "parent").join(lost.withColumnRenamed("id", "parent"), "parent").select("id", "sid")))
        levels.append(child)
    out = levels[0].select("tokens", "absent", "support")
    for x in levels[1:-1]:
        out = out.unionAll(x.select("tokens", "absent", "support"))
    of_gap = lambda i: F.transform(F.filter("absent", lambda x: x["gap"] == i - 1), lambda x: x["q"])
    token = lambda neg, x: F.struct(F.lit(neg).alias("neg"), x.alias("items"))
    whole = F.flatten(F.transform("tokens", lambda t, i: F.when(F.size(of_gap(i)) > 0, F.array(token(True, of_gap(i)), token(False, t["items"]))).otherwise(F.array(token(False, t["items"])))))
    return positive.unionByName(described(out.select(whole.cast(TOKENS).alias("tokens"), "support")))


def mine_levelwise(sequences: DataFrame, sigma, sem: Semantics = GROWTH, max_items: int = 3, max_neg_size: int | None = 1, c: Constraints = FREE) -> DataFrame:
    """pattern, support, n_items, n_pos, n_neg by generate and test: candidates of each size come from frequent patterns, one scan counts them all. Complete for soft occurrence and total absence."""
    n = sequences.count()
    minsup = max(1, threshold(n, sigma))
    names = [r[0] for r in sequences.select(F.explode(F.array_distinct(F.flatten("itemsets"))).alias("x")).groupBy("x").count().where(F.col("count") >= minsup).orderBy("x").select("x").collect()]
    level = [Pattern((Element(False, (x,)),)) for x in names]
    found: list[tuple[str, int, int, int, int]] = []
    while level:
        counted = _count(sequences, level, sem, c)
        kept = [(p, counted[p.text]) for p in level if counted.get(p.text, 0) >= minsup]
        found += [(p.text, s, p.stats["n_items"], p.stats["n_itemsets"], p.stats["n_neg"]) for p, s in kept]
        level = [q for p, _ in kept for q in _extensions(p, names, max_items, max_neg_size)]
        if len(level) > BROADCAST_ROWS:
            raise ValueError(f"{len(level)} candidates do not fit a broadcast; raise the threshold or lower max_items")
    return sequences.sparkSession.createDataFrame(found, "pattern string, support long, n_items int, n_pos int, n_neg int")


def _extensions(p: Pattern, names: list[str], max_items: int, max_neg_size: int | None) -> list[Pattern]:
    e = p.elements
    if p.stats["n_items"] >= max_items:
        return []
    out = [Pattern((*e[:-1], Element(False, (*e[-1].items, x)))) for x in names if x > e[-1].items[-1]]
    out += [Pattern((*e, Element(False, (x,)))) for x in names]
    if len(p.positives) >= 2 and len(e[-1].items) == 1:
        held = e[-2].items if e[-2].neg else ()
        if max_neg_size is None or len(held) < max_neg_size:
            front = e[:-2] if held else e[:-1]
            out += [Pattern((*front, Element(True, (*held, q)), e[-1])) for q in names if not held or q > held[-1]]
    return out


def _count(sequences: DataFrame, patterns: list[Pattern], sem: Semantics, c: Constraints) -> dict[str, int]:
    shared = sequences.sparkSession.sparkContext.broadcast(patterns)

    def run(parts):
        total: dict[str, int] = {}
        for pdf in parts:
            for sets in pdf["itemsets"]:
                sets = [frozenset(s) for s in sets]
                have = frozenset().union(*sets)
                for p in shared.value:
                    if all(x in have for items in p.positives for x in items) and occurs(sets, p, sem, c):
                        total[p.text] = total.get(p.text, 0) + 1
        yield pd.DataFrame({"pattern": list(total), "n": list(total.values())}).astype({"pattern": "string", "n": "int64"})

    rows = sequences.select("itemsets").mapInPandas(run, "pattern string, n long").groupBy("pattern").agg(F.sum("n").alias("n"))
    return {r["pattern"]: r["n"] for r in rows.collect()}


def language(names: list[str], max_items: int, max_neg_size: int | None = None) -> list[Pattern]:
    """Every pattern of at most max_items items over the names. Exponential; for tests."""
    def sets(limit: int) -> list[tuple[str, ...]]:
        return [x for k in range(1, limit + 1) for x in combinations(names, k)]

    def go(elements: tuple[Element, ...], room: int) -> list[Pattern]:
        out = [Pattern(elements)]
        for neg in ((), *sets(room - 1 if max_neg_size is None else min(max_neg_size, room - 1))):
            for pos in sets(room - len(neg)):
                out += go((*elements, *([Element(True, neg)] if neg else []), Element(False, pos)), room - len(neg) - len(pos))
        return out

    return [p for pos in sets(max_items) for p in go((Element(False, pos),), max_items - len(pos))]


def mine_exhaustive(sequences: list[list[list[str]]], minsup: int, max_items: int, sem: Semantics = GROWTH, c: Constraints = FREE, max_neg_size: int | None = None) -> dict[str, int]:
    names = sorted({x for s in sequences for y in s for x in y if sum(any(x in z for z in t) for t in sequences) >= minsup})
    out = {}
    for p in language(names, max_items, max_neg_size):
        n = sum(occurs(s, p, sem, c) for s in sequences)
        if n >= minsup:
            out[p.text] = n
    return out


__all__ = ["language", "mine_exhaustive", "mine_levelwise", "mine_partner", "mine_positive", "mine_positive_library", "mine_strict", "parse", "partner_candidates"]
