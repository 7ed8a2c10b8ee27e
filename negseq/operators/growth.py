"""The growth miner: prefix growth with absences, level by level over a frontier.

A frontier row (fid, sid, start, ppred, pos) says that a pattern of the class fid ends
in sequence sid at pos, its previous positive itemset at ppred and its first at start. For one end
only the largest ppred matters, as a smaller window lacks whatever a larger one lacks;
with maxspan the pairs (ppred, start) that no other pair beats are kept. A negative step is then a
filter of rows, and no sequence is searched again.

Absences are counted by their violators: only items that do occur in the windows make
rows. A pattern with an absence that is violated nowhere shares the frontier of its parent, so fid is
a class of patterns with equal frontiers, and a large alphabet costs pattern rows only.

Items are coded as integers in lexicographic order, positions are kept as they are when infrequent
items go. Store and frontiers are partitioned by sid, so extension and support counting need no
exchange; only counts travel.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.pattern import TOKENS, stats, text_of
from ..plans.planner import LOCAL_ROWS, small
from ..plans.stage import bucketed, cached, written


def threshold(sequences: int, sigma: str | float | int) -> int:
    """Least number of sequences: an absolute number as it is, a share by exact ceiling."""
    if isinstance(sigma, int):
        return sigma
    share = Fraction(str(sigma))
    return -((-sequences * share.numerator) // share.denominator)


@dataclass(frozen=True)
class Options:
    """surround: 'off', 'printed' (no absence of an item that stands beside it, judged when the absence is added) or 'checked' (also when the last itemset grows). redundancy 'drop_last': no absence of an item of the last itemset. non_inclusion 'partial' takes whole absences from lminus."""

    maxgap: int | None = None
    maxspan: int | None = None
    max_items: int | None = 3
    max_itemsets: int | None = None
    max_pos_items: int | None = None
    max_neg_size: int | None = 1
    negatives: bool = True
    surround: str = "off"
    redundancy: str | None = None
    non_inclusion: str = "total"
    embedding: str = "soft"
    prefix: str | None = None


def check(o: Options) -> Options:
    if o.surround not in ("off", "printed", "checked") or o.redundancy not in (None, "drop_last") or o.non_inclusion not in ("total", "partial"):
        raise ValueError(f"unknown option in {o}")
    return o


def frequent_items(items: DataFrame, minsup: int) -> DataFrame:
    """item, support: sequences that hold it."""
    return items.select("sid", "item").distinct().groupBy("item").agg(F.count("*").alias("support")).where(F.col("support") >= minsup)


def n_sequences(items: DataFrame) -> int:
    return items.select("sid").distinct().count()


def dictionary(frequent: DataFrame) -> DataFrame:
    """id, item, support; ids follow the order of the items (ranges numbered in two steps would do for huge alphabets)."""
    return frequent.select(F.row_number().over(Window.orderBy("item")).alias("id"), "item", "support")


def encode(items: DataFrame, words: DataFrame, n_words: int, buckets: int | None = None) -> DataFrame:
    """(sid, pos, item id) of the frequent items, partitioned by sid."""
    coded = items.join(small(words.select("id", "item"), n_words), "item").select("sid", "pos", F.col("id").alias("item"))
    if buckets:
        return bucketed(coded, "sid", ["sid", "pos"], buckets)
    return cached(coded.repartition("sid"))


_EMPTY = "cast(null as int)"


def _append(tokens: Column, item: Column, op: Column) -> Column:
    """Tokens after composition c, sequence s or negation n with an item."""
    last = F.element_at(tokens, -1)
    init = F.slice(tokens, 1, F.size(tokens) - 1)
    one = lambda neg, items: F.array(F.struct(F.lit(neg).alias("neg"), items.alias("items")))
    before = F.get(tokens, F.size(tokens) - 2)
    more = F.concat(F.slice(tokens, 1, F.greatest(F.size(tokens) - 2, F.lit(0))), one(True, F.concat(before["items"], F.array(item))), F.array(last))
    new = F.concat(init, one(True, F.array(item)), F.array(last))
    return (
        F.when(op == "c", F.concat(init, one(False, F.concat(last["items"], F.array(item)))))
        .when(op == "s", F.concat(tokens, one(False, F.array(item))))
        .when(F.coalesce(before["neg"], F.lit(False)), more)
        .otherwise(new)
    )


class Miner:
    def __init__(self, items: DataFrame, minsup: int, options: Options, lminus: DataFrame | None = None, buckets: int | None = None):
        self.o, self.minsup, self.buckets, self.spark = check(options), minsup, buckets, items.sparkSession
        self.words = cached(dictionary(frequent_items(items, minsup)))
        self.n_words = self.words.count()
        self.store = encode(items, self.words, self.n_words, buckets)
        self.lminus = lminus
        self.kept: list[DataFrame] = []
        self.frontier_rows: list[int] = []
        self.levels: list[DataFrame] = []
        self.frontiers: list[DataFrame] = []

    # level tables: fid, pid, parent, op, item, tokens, support, last, last_size, neg, neg_size, npos

    def seed(self) -> tuple[DataFrame, DataFrame]:
        fid = F.xxhash64(F.lit("seed"), "id")
        words = self.words if self.o.prefix is None else self.words.where(F.col("item") == self.o.prefix)
        p = words.select(
            fid.alias("fid"), F.xxhash64("item").alias("pid"), F.lit(None).cast("long").alias("parent"), F.lit("root").alias("op"), F.col("id").alias("item"),
            F.array(F.struct(F.lit(False).alias("neg"), F.array("item").alias("items"))).cast(TOKENS).alias("tokens"),
            "support", F.col("id").alias("last"), F.lit(1).alias("last_size"), F.lit(None).cast("int").alias("neg"), F.lit(0).alias("neg_size"), F.lit(1).alias("npos"),
        )
        roots = words.select("id", fid.alias("fid"))
        f = self.store.join(small(roots, self.n_words), F.col("item") == F.col("id"))
        start = F.col("pos") if self.o.maxspan is not None else F.expr(_EMPTY)
        return p, f.select("fid", "sid", start.alias("start"), F.expr(_EMPTY).alias("ppred"), "pos")

    def keep(self, df: DataFrame) -> tuple[DataFrame, int]:
        """Cut the lineage: a plan that nests all levels before it doubles with each. Frontiers go to buckets of sid if the store is in buckets."""
        df = bucketed(df, "sid", ["sid", "pos"], self.buckets) if self.buckets and "sid" in df.columns else written(df)
        return df, df.count()

    def positive_candidates(self, f: DataFrame, ops: DataFrame, n_ops: int) -> DataFrame:
        """(fid, op, item, sid, start, ppred, pos), not pruned. ops: fid, last, compose, extend."""
        o, s = self.o, self.store.select(F.col("sid").alias("_sid"), F.col("pos").alias("at"), F.col("item").alias("next"))
        f = f.join(small(ops, n_ops), "fid")
        same = f.where("compose").join(s, (F.col("sid") == F.col("_sid")) & (F.col("pos") == F.col("at")) & (F.col("next") > F.col("last")))
        same = same.select("fid", F.lit("c").alias("op"), F.col("next").alias("item"), "sid", "start", "ppred", "pos")
        reach = (F.col("sid") == F.col("_sid")) & (F.col("at") > F.col("pos"))
        if o.maxgap is not None:
            reach &= F.col("at") <= F.col("pos") + o.maxgap
        if o.maxspan is not None:
            reach &= F.col("at") - F.col("start") <= o.maxspan
        after = f.where("extend").join(s, reach)
        after = after.select("fid", F.lit("s").alias("op"), F.col("next").alias("item"), "sid", "start", F.col("pos").alias("ppred"), F.col("at").alias("pos"))
        return same.unionAll(after)

    def pruned(self, rows: DataFrame) -> DataFrame:
        """For each end, the largest ppred, or the pairs (ppred, start) that none beats."""
        if self.o.maxspan is None:
            return rows.groupBy("fid", "sid", "pos").agg(F.max("ppred").alias("ppred")).select("fid", "sid", F.expr(_EMPTY).alias("start"), "ppred", "pos")
        by = Window.partitionBy("fid", "sid", "pos").orderBy(F.col("ppred").desc(), F.col("start").desc()).rowsBetween(Window.unboundedPreceding, -1)
        better = F.max("start").over(by)
        return rows.distinct().withColumn("_b", better).where("_b is null or start > _b").select("fid", "sid", "start", "ppred", "pos")

    def violated(self, f: DataFrame) -> DataFrame:
        """(fid, sid, start, ppred, pos, q): rows whose window holds q; q is an item id, or the number of a set of lminus."""
        s = self.store.select(F.col("sid").alias("_sid"), F.col("pos").alias("at"), F.col("item").alias("q"))
        inside = f.join(s, (F.col("sid") == F.col("_sid")) & (F.col("at") > F.col("ppred")) & (F.col("at") < F.col("pos")))
        row = ["fid", "sid", "start", "ppred", "pos"]
        if self.o.non_inclusion == "total":
            return inside.select(*row, "q").distinct()
        member = self.sets.select(F.explode("ids").alias("q"), F.col("set").alias("_set"), F.size("ids").alias("_size"))
        inside = inside.select(*row, "at", "q").distinct().join(small(member, self.n_sets), "q")
        unit = ["at"] if self.o.embedding == "soft" else []
        found = inside.groupBy(*row, *unit, "_set", "_size").agg(F.count_distinct("q").alias("_n")).where("_n = _size")
        return found.select(*row, F.col("_set").alias("q")).distinct()

    def load_lminus(self) -> None:
        """Sets to be absent as ids: the given ones that consist of frequent items only in part keep what is frequent under total; unknown items make a partial absence always true."""
        if self.lminus is None:
            sets = self.words.select(F.array("item").alias("items"))
        else:
            sets = self.lminus.select(F.array_sort(F.array_distinct("items")).alias("items")).where(F.size("items") > 0).distinct()
        self.sets = sets.withColumn("set", F.row_number().over(Window.orderBy(text_of(F.array(F.struct(F.lit(True).alias("neg"), F.col("items")))))))
        each = self.sets.select("set", "items", F.explode("items").alias("item")).join(small(self.words.select("id", "item"), self.n_words), "item", "left")
        ids = each.groupBy("set", "items").agg(F.array_sort(F.collect_list(F.coalesce("id", F.lit(0)))).alias("ids"))
        if self.o.max_neg_size is not None:
            ids = ids.where(F.size("ids") <= self.o.max_neg_size)
        self.sets = cached(ids)
        self.n_sets = self.sets.count()

    def negative_children(self, p: DataFrame, f: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame] | None:
        """Children by an absence in the last gap: their level table, the frontier rows of those that lose rows, and the classes of these."""
        o = self.o
        ready = p.where((F.col("npos") >= 2) & (F.col("last_size") == 1))
        if o.max_neg_size is not None:
            ready = ready.where(F.col("neg_size") < o.max_neg_size) if o.non_inclusion == "total" else ready.where("neg is null")
        elif o.non_inclusion == "partial":
            ready = ready.where("neg is null")
        if ready.isEmpty():
            return None
        rows = f.join(ready.select("fid").distinct(), "fid", "left_semi")
        bad = written(self.violated(rows))
        of = bad.groupBy("fid", "sid", "q").agg(F.count("*").alias("bad"))
        all_ = rows.groupBy("fid", "sid").agg(F.count("*").alias("rows"))
        counts = of.join(all_, ["fid", "sid"]).groupBy("fid", "q").agg(F.sum(F.when(F.col("bad") == F.col("rows"), 1).otherwise(0)).alias("lost"))
        if o.non_inclusion == "total":
            options = self.words.select(F.col("id").alias("q"), F.array("item").alias("absent"), F.lit(1).alias("more"))
            n_options = self.n_words
            if self.lminus is not None:
                single = self.sets.where(F.size("items") == 1).select(F.element_at("ids", 1).alias("q"))
                options = options.join(single, "q", "left_semi")
        else:
            options, n_options = self.sets.select(F.col("set").alias("q"), F.col("items").alias("absent"), F.size("items").alias("more")), self.n_sets
        child = ready.crossJoin(small(options, n_options))
        if o.non_inclusion == "total":
            child = child.where("neg is null or q > neg")
        n_items = stats("tokens")["n_items"]
        if o.max_items is not None:
            child = child.where(n_items + F.col("more") <= o.max_items)
        t = F.col("tokens")
        left = F.when(F.col("neg").isNull(), F.get(t, F.size(t) - 2)).otherwise(F.get(t, F.size(t) - 3))["items"]
        right = F.element_at(t, -1)["items"]
        if o.surround != "off":
            child = child.where(~F.arrays_overlap("absent", F.concat(left, right)))
        if o.redundancy == "drop_last":
            child = child.where(~F.arrays_overlap("absent", right))
        child = child.join(counts.withColumnRenamed("fid", "_fid").withColumnRenamed("q", "_q"), (F.col("fid") == F.col("_fid")) & (F.col("q") == F.col("_q")), "left")
        child = child.withColumn("support", F.col("support") - F.coalesce("lost", F.lit(0))).where(F.col("support") >= self.minsup)
        if o.non_inclusion == "total":
            tokens = _append(t, F.element_at("absent", 1), F.lit("n"))
        else:
            tokens = F.concat(F.slice(t, 1, F.size(t) - 1), F.array(F.struct(F.lit(True).alias("neg"), F.col("absent").alias("items"))), F.array(F.element_at(t, -1)))
        fid = F.when(F.col("lost").isNull(), F.col("fid")).otherwise(F.xxhash64("fid", F.lit("n"), "q"))
        child = child.select(
            "fid", fid.alias("new"), "q", F.xxhash64("pid", F.lit("n"), "q").alias("pid"), F.col("pid").alias("parent"), F.lit("n").alias("op"), F.col("q").alias("item"), tokens.cast(TOKENS).alias("tokens"),
            "support", "last", "last_size", F.col("q").alias("neg"), (F.col("neg_size") + F.col("more")).alias("neg_size"), "npos",
        )
        child = written(child)
        fresh = child.where("new <> fid").select("fid", "q", "new").distinct()
        row = ["fid", "sid", "ppred", "pos"] + (["start"] if o.maxspan is not None else [])
        moved = rows.join(small(fresh, fresh.count()), "fid").join(bad.select(*row, "q"), [*row, "q"], "left_anti")
        return child.drop("fid", "q").withColumnRenamed("new", "fid"), moved.select(F.col("new").alias("fid"), "sid", "start", "ppred", "pos"), fresh.select(F.col("new").alias("fid"))

    def positive_children(self, p: DataFrame, f: DataFrame, n: int) -> tuple[DataFrame, DataFrame]:
        o = self.o
        s = stats("tokens")
        room = F.lit(True) if o.max_items is None else s["n_items"] < o.max_items
        if o.max_pos_items is not None:
            room &= F.aggregate(F.filter("tokens", lambda t: ~t["neg"]), F.lit(0), lambda a, t: a + F.size(t["items"])) < o.max_pos_items
        extend = room & (F.lit(True) if o.max_itemsets is None else F.col("npos") < o.max_itemsets)
        able = p.withColumn("compose", room).withColumn("extend", extend).where("compose or extend")
        ops = able.groupBy("fid", "last").agg(F.max("compose").alias("compose"), F.max("extend").alias("extend"))
        rows = self.positive_candidates(f, ops, n)
        counts = rows.select("fid", "op", "item", "sid").distinct().groupBy("fid", "op", "item").agg(F.count("*").alias("n")).where(F.col("n") >= self.minsup)
        counts = written(counts)
        n_counts = counts.count()
        child = able.drop("item", "op").join(small(counts, n_counts), "fid").where(F.when(F.col("op") == "c", F.col("compose")).otherwise(F.col("extend")))
        child = child.join(small(self.words.select("id", F.col("item").alias("word")), self.n_words), F.col("item") == F.col("id"))
        if o.surround == "checked":
            before = F.get("tokens", F.size("tokens") - 2)
            child = child.where((F.col("op") == "s") | ~F.coalesce(before["neg"] & F.array_contains(before["items"], F.col("word")), F.lit(False)))
        new = F.xxhash64("fid", "op", "item")
        composed = F.col("op") == "c"
        child = child.select(
            new.alias("fid"), F.xxhash64("pid", "op", "item").alias("pid"), F.col("pid").alias("parent"), "op", "item", _append(F.col("tokens"), F.col("word"), F.col("op")).cast(TOKENS).alias("tokens"),
            F.col("n").alias("support"), F.col("item").alias("last"), F.when(composed, F.col("last_size") + 1).otherwise(1).alias("last_size"),
            F.when(composed, F.col("neg")).alias("neg"), F.when(composed, F.col("neg_size")).otherwise(0).alias("neg_size"), F.when(composed, F.col("npos")).otherwise(F.col("npos") + 1).alias("npos"),
        )
        alive = counts.select("fid", "op", "item")
        moved = rows.join(small(alive, n_counts), ["fid", "op", "item"], "left_semi").select(new.alias("fid"), "sid", "start", "ppred", "pos")
        return child, self.pruned(moved)

    def run(self, all_frontiers: bool = False) -> DataFrame:
        """All levels: pid, parent, op, item, tokens, support. The frontier of the last level is made only if asked for."""
        o = self.o
        if o.negatives:
            self.load_lminus()
        p, f = self.seed()
        (p, n), (f, n_rows) = self.keep(p), self.keep(f)
        # partial absences add several items at once, so a level holds the patterns found in the same number of steps
        while True:
            self.levels.append(p)
            self.frontiers.append(f)
            self.frontier_rows.append(n_rows)
            if not n or len(self.levels) >= (o.max_items or 10**6):
                break
            child, moved = self.positive_children(p, f, n)
            if o.negatives and (negative := self.negative_children(p, f)) is not None:
                more, rows, fresh = negative
                # rows of a class that is made anew at this level must not come twice
                made = child.select("fid").unionAll(fresh)
                shared = f.join(more.select("fid").distinct(), "fid", "left_semi").join(made, "fid", "left_anti")
                child, moved = child.unionByName(more), moved.unionAll(rows).unionAll(shared)
            p, n = self.keep(child)
            if not n:
                break
            if len(self.levels) + 1 == o.max_items and not all_frontiers:
                self.levels.append(p)
                break
            f, n_rows = self.keep(moved)
        return self.levels[0] if len(self.levels) == 1 else _union([x.select("pid", "parent", "op", "item", "tokens", "support") for x in self.levels])


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0].select("pid", "parent", "op", "item", "tokens", "support")
    for x in parts[1:]:
        out = out.unionAll(x.select("pid", "parent", "op", "item", "tokens", "support"))
    return out


def described(found: DataFrame, n: int | None = None) -> DataFrame:
    """pattern, support, n_items, n_pos, n_neg, tokens (and rel_support)."""
    s = stats("tokens")
    out = found.select(text_of("tokens").alias("pattern"), F.col("support").cast("long").alias("support"), s["n_items"].alias("n_items"), s["n_itemsets"].alias("n_pos"), s["n_neg"].alias("n_neg"), "tokens")
    return out if n is None else out.withColumn("rel_support", F.round(F.col("support") / n, 6))


def size_of(items: DataFrame) -> tuple[int, int]:
    """Sequences and rows, in one pass."""
    n, rows = items.groupBy("sid").agg(F.count("*").alias("rows")).agg(F.count("*"), F.coalesce(F.sum("rows"), F.lit(0))).first()
    return n, rows


def mine(items: DataFrame, sigma: str | float | int, options: Options | None = None, lminus: DataFrame | None = None, buckets: int | None = None, sequences: int | None = None, engine: str = "auto", packed=None) -> DataFrame:
    """pattern, support, n_items, n_pos, n_neg, tokens of all frequent patterns. items: sid, pos, item; sequences: n(D) if some sequences are empty; packed: items as bit_engine.pack gives them, if they are there already.

    engine: 'frontier', 'bits', or 'auto': a database that was counted to hold at most planner.LOCAL_ROWS events is mined
    depth-first in tasks that share it, a larger one level by level on bits, if the options allow; all give the same patterns.
    """
    from . import bit_engine, local_engine

    if engine not in ("auto", "frontier", "bits"):
        raise ValueError(f"unknown engine {engine}")
    o = check(options or Options())
    if engine == "frontier" or buckets is not None or not bit_engine.able(o):
        if engine == "bits":
            raise ValueError("bits express neither maxspan nor buckets")
        n = n_sequences(items) if sequences is None else sequences
        return described(Miner(items, max(1, threshold(n, sigma)), o, lminus, buckets).run())
    packed = bit_engine.pack(items) if packed is None else packed
    minsup = max(1, threshold(packed.n if sequences is None else sequences, sigma))
    if engine == "auto" and packed.events <= LOCAL_ROWS:
        if lminus is None and local_engine.able(o):
            return described(local_engine.mine_small(items, minsup, o))
    elif bit_engine.fits(packed, minsup, n_sets := 0 if lminus is None else lminus.count()):
        sets = [tuple(r[0]) for r in lminus.select("items").collect()] if n_sets else None if lminus is None else []
        return described(bit_engine.mine_packed(packed, minsup, o, sets))
    elif engine == "bits":
        raise ValueError("a sequence or the sets to be absent do not fit a task")
    return described(Miner(items, minsup, o, lminus).run())


def trace(items: DataFrame, sigma: str | float | int, options: Options | None = None) -> DataFrame:
    """The search tree: pattern, parent_pattern, op, support. A pattern's last step shows in its end: an itemset of several items was composed, an absence before a single one was added after it."""
    t = F.col("tokens")
    last, before = F.element_at(t, -1), F.get(t, F.size(t) - 2)
    one = lambda neg, x: F.array(F.struct(F.lit(neg).alias("neg"), F.slice(x, F.lit(1), F.size(x) - 1).alias("items")))
    front = lambda n: F.slice(t, F.lit(1), F.greatest(F.size(t) - n, F.lit(0)))
    op = F.when(F.size(last["items"]) > 1, "c").when(F.size(t) == 1, "root").when(before["neg"], "n").otherwise("s")
    less = F.when(F.size(before["items"]) > 1, F.concat(front(2), one(True, before["items"]), F.array(last))).otherwise(F.concat(front(2), F.array(last)))
    parent = F.when(op == "c", F.concat(front(1), one(False, last["items"]))).when(op == "n", less).when(op == "s", front(1))
    return mine(items, sigma, options).select("pattern", F.when(op != "root", text_of(parent.cast(TOKENS))).alias("parent_pattern"), op.alias("op"), "support")


def with_sids(items: DataFrame, minsup: int, options: Options) -> DataFrame:
    """tokens, pattern, sid of every frequent pattern, from the frontiers."""
    miner = Miner(items, minsup, options)
    miner.run(all_frontiers=True)
    out = None
    for p, f in zip(miner.levels, miner.frontiers, strict=False):
        rows = p.select("fid", "tokens").join(f.select("fid", "sid").distinct(), "fid").select("tokens", text_of("tokens").alias("pattern"), "sid")
        out = rows if out is None else out.unionAll(rows)
    return out


def frequent_itemsets(items: DataFrame, minsup: int, max_size: int, packed=None) -> DataFrame:
    """items array: sets that stand together in one itemset of enough sequences, level-wise. packed: as for mine."""
    found = mine(items, minsup, Options(max_items=max_size, max_itemsets=1, negatives=False), packed=packed)
    return found.select(F.element_at("tokens", 1)["items"].alias("items"), "support")
