"""Depth-first mining on arrays: of a whole database that is small, or of the roots that are.

A branch is two arrays, the live ends of a pattern and for each end the nearest previous
end, over a store of events sorted by sequence, position and item. A step looks all
remaining events up among the ends at once, so the cost of a pattern is a few vector
operations over its projected events. A branch belongs to one root item, so roots, and
the first steps below a root, are mined in different tasks.

A database of up to ``planner.LOCAL_ROWS`` events (counted first) is broadcast to the tasks. In a larger one a
root whose sequences hold no more events than that is shipped to a task of its own, and
larger roots go to the frontier engine.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.pattern import TOKENS
from ..plans import planner
from ..plans.stage import written
from .growth import Options, described, frequent_items, n_sequences, threshold

Tokens = tuple[tuple[bool, tuple[int, ...]], ...]
#: Patterns of a batch that a task returns.
BATCH = 50_000


def able(o: Options) -> bool:
    """Whether the arrays express the options: not maxspan, whose ends need pairs, nor partial absence."""
    return o.maxspan is None and o.non_inclusion == "total"


@dataclass
class Store:
    """key: place of an event's itemset, ascending over all sequences; base: the place before its sequence's first; item: from 0, in the order of names."""

    key: np.ndarray
    base: np.ndarray
    item: np.ndarray
    names: list[str]

    @classmethod
    def of(cls, sid: np.ndarray, pos: np.ndarray, item: np.ndarray, names: list[str]) -> Store:
        order = np.lexsort((item, pos, sid))
        sid, pos, item = sid[order], pos[order].astype(np.int64), item[order]
        if len(sid):
            new = np.r_[True, (sid[1:] != sid[:-1]) | (pos[1:] != pos[:-1]) | (item[1:] != item[:-1])]
            sid, pos, item = sid[new], pos[new], item[new]
        first = np.flatnonzero(np.r_[True, sid[1:] != sid[:-1]]) if len(sid) else np.zeros(0, int)
        length = pos[np.r_[first[1:], len(sid)] - 1] if len(first) else np.zeros(0, np.int64)
        base = np.repeat(np.cumsum(length + 1) - length - 1, np.diff(np.r_[first, len(sid)]))
        return cls(base + pos, base, item.astype(np.int32), names)

    @classmethod
    def read(cls, rows: pa.Table, minsup: int) -> Store:
        """Of rows (sid, pos, item) the items that enough sequences hold."""
        words = rows.column("item").combine_chunks().dictionary_encode()
        words = words.combine_chunks() if isinstance(words, pa.ChunkedArray) else words
        sid, pos, code = rows.column("sid").to_numpy(), rows.column("pos").to_numpy(), words.indices.to_numpy(zero_copy_only=False)
        _, sid = np.unique(sid, return_inverse=True)
        names = words.dictionary.to_pylist()
        held = np.unique(sid.astype(np.int64) * max(len(names), 1) + code)
        support = np.bincount(held % max(len(names), 1), minlength=len(names))
        kept = sorted((i for i in range(len(names)) if support[i] >= minsup), key=lambda i: names[i])
        new = np.full(len(names), -1)
        new[kept] = np.arange(len(kept))
        code = new[code] if len(code) else code.astype(np.int64)
        has = code >= 0
        return cls.of(sid[has], pos[has], code[has], [names[i] for i in kept])


class Branches:
    """Mines the roots of a store. ``found`` gets (tokens, support, ends of the sequences or None)."""

    def __init__(self, store: Store, minsup: int, o: Options, found: Callable[[Tokens, int, np.ndarray | None], None], with_sids: bool = False):
        self.s, self.minsup, self.o, self.found, self.with_sids = store, minsup, o, found, with_sids
        self.places: list[np.ndarray] | None = None
        self.order = np.arange(len(store.names))

    def root(self, item: int, part: int = 0, parts: int = 1) -> None:
        """The branch of a root item; with parts, those of the steps below it whose number falls to the part."""
        s = self.s
        at = np.flatnonzero(s.item == item)
        ends, base = s.key[at], s.base[at]
        support = int((np.diff(base, prepend=-1) != 0).sum())
        if support < self.minsup:
            return
        tokens = ((False, (item,)),)
        if part == 0:
            self.report(tokens, support, base)
        if self.o.max_items is None or self.o.max_items > 1:
            self.grow(tokens, 1, 1, ends, base, base, np.arange(len(s.key)), (part, parts))

    def report(self, tokens: Tokens, support: int, base: np.ndarray) -> None:
        self.found(tokens, support, np.unique(base) if self.with_sids else None)

    def grow(self, tokens: Tokens, n_items: int, npos: int, ends: np.ndarray, before: np.ndarray, base: np.ndarray, events: np.ndarray, share: tuple[int, int] = (0, 1)) -> None:
        """Children of a pattern that may take one item more. ends, before, base: of each live end its place, the previous one, and the place before its sequence; events: those of live sequences at or behind their first end, and perhaps more."""
        o, s = self.o, self.s
        leaf = o.max_items is not None and n_items + 1 >= o.max_items
        last = tokens[-1][1]
        neg = tokens[-2][1] if len(tokens) > 1 and tokens[-2][0] else ()
        if o.negatives and npos >= 2 and len(last) == 1 and (o.max_neg_size is None or len(neg) < o.max_neg_size):
            self.absences(tokens, n_items, npos, neg, ends, before, base, events, leaf)
        if o.max_pos_items is not None and sum(len(x) for n, x in tokens if not n) >= o.max_pos_items:
            return
        key, start, item = s.key[events], s.base[events], s.item[events]
        at = np.searchsorted(ends, key, "right") - 1
        live = (at >= 0) & (ends[at] > start)
        events, key, start, item, at = events[live], key[live], start[live], item[live], at[live]
        same = ends[at] == key
        number = 0
        more = same & (item > last[-1])
        for x, k in self.by_item(item, start, more):
            if o.surround == "checked" and x in neg:
                continue
            number += 1
            if number % share[1] == share[0]:
                child = (*tokens[:-1], (False, (*last, x)))
                self.report(child, self.held(start[k]), start[k])
                if not leaf:
                    self.grow(child, n_items + 1, npos, key[k], before[at[k]], start[k], events)
        if o.max_itemsets is not None and npos >= o.max_itemsets:
            return
        # the nearest end that lies before the event
        at = np.where(same, at - 1, at)
        after = (at >= 0) & (ends[at] > start)
        if o.maxgap is not None:
            after &= key - ends[at] <= o.maxgap
        for x, k in self.by_item(item, start, after):
            number += 1
            if number % share[1] == share[0]:
                child = (*tokens, (False, (x,)))
                self.report(child, self.held(start[k]), start[k])
                if not leaf:
                    self.grow(child, n_items + 1, npos + 1, key[k], ends[at[k]], start[k], events)

    @staticmethod
    def held(base: np.ndarray) -> int:
        """Sequences among ends in order."""
        return int((base[1:] != base[:-1]).sum()) + 1 if len(base) else 0

    def by_item(self, item: np.ndarray, base: np.ndarray, wanted: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """(item, places of its events) of the items that enough sequences hold among the wanted events, which are in order of sequence and place."""
        at = np.flatnonzero(wanted)
        if len(at) < self.minsup:
            return
        order = np.argsort(item[at], kind="stable")
        at = at[order]
        x, b = item[at], base[at]
        edge = np.flatnonzero(np.r_[True, x[1:] != x[:-1]])
        new = np.r_[True, (b[1:] != b[:-1]) | (x[1:] != x[:-1])]
        for first, end, n in zip(edge, np.r_[edge[1:], len(at)], np.add.reduceat(new, edge), strict=True):
            if n >= self.minsup:
                yield int(x[first]), at[first:end]

    def violated(self, before: np.ndarray, ends: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """(item, rows whose window holds it) of each item that is in some window: from the windows' events if these are few, otherwise by looking each item's last place before the ends up."""
        s = self.s
        low, high = np.searchsorted(s.key, before, "right"), np.searchsorted(s.key, ends, "left")
        width = high - low
        if width.sum() > 4 * len(ends) * len(s.names):
            if self.places is None:
                by = np.argsort(s.item, kind="stable")
                self.places = np.split(s.key[by], np.searchsorted(s.item[by], self.order[1:]))
            for q, places in enumerate(self.places):
                at = np.searchsorted(places, ends, "left") - 1
                rows = np.flatnonzero((at >= 0) & (places[at] > before))
                if len(rows):
                    yield q, rows
            return
        row = np.repeat(np.arange(len(ends)), width)
        event = np.arange(len(row)) - np.repeat(np.cumsum(width) - width, width) + np.repeat(low, width)
        pair = np.unique(s.item[event].astype(np.int64) * len(ends) + row)
        q, row = pair // max(len(ends), 1), pair % max(len(ends), 1)
        edge = np.flatnonzero(np.r_[True, q[1:] != q[:-1]]) if len(q) else np.zeros(0, int)
        for first, end in zip(edge, np.r_[edge[1:], len(q)], strict=False):
            yield int(q[first]), row[first:end]

    def absences(self, tokens: Tokens, n_items: int, npos: int, neg: tuple[int, ...], ends: np.ndarray, before: np.ndarray, base: np.ndarray, events: np.ndarray, leaf: bool) -> None:
        o = self.o
        last = tokens[-1][1]
        around = {*last, *(tokens[-3][1] if neg else tokens[-2][1])} if o.surround != "off" else set(last) if o.redundancy == "drop_last" else set()
        least = neg[-1] if neg else -1
        whole = self.held(base)
        bad = dict(self.violated(before, ends))
        for q in range(least + 1, len(self.s.names)):
            if q in around:
                continue
            child = (*tokens[: -2 if neg else -1], (True, (*neg, q)), tokens[-1])
            rows = bad.get(q)
            if rows is None:
                self.report(child, whole, base)
                if not leaf:
                    self.grow(child, n_items + 1, npos, ends, before, base, events)
                continue
            keep = np.ones(len(ends), bool)
            keep[rows] = False
            left = base[keep]
            support = self.held(left)
            if support >= self.minsup:
                self.report(child, support, left)
                if not leaf:
                    self.grow(child, n_items + 1, npos, ends[keep], before[keep], left, events)


class Found:
    """Patterns as Arrow batches (tokens, support)."""

    def __init__(self, names: list[str]):
        self.names, self.rows = np.array(names, object), []

    def __call__(self, tokens: Tokens, support: int, _: np.ndarray | None = None) -> None:
        self.rows.append((tokens, support))

    def batches(self) -> Iterator[pa.RecordBatch]:
        for at in range(0, len(self.rows), BATCH):
            part = self.rows[at : at + BATCH]
            lists = lambda flat, sizes: pa.ListArray.from_arrays(pa.array(np.cumsum([0, *sizes]), pa.int32()), flat)
            each = [e for tokens, _ in part for e in tokens]
            items = lists(pa.array(self.names[[i for _, x in each for i in x]], pa.string()), [len(x) for _, x in each])
            struct = pa.StructArray.from_arrays([pa.array([n for n, _ in each], pa.bool_()), items], ["neg", "items"])
            yield pa.RecordBatch.from_arrays([lists(struct, [len(t) for t, _ in part]), pa.array([n for _, n in part], pa.int64())], ["tokens", "support"])
        self.rows = []


FOUND = f"tokens {TOKENS}, support long"


def mine_store(spark, store: Store, minsup: int, o: Options) -> DataFrame:
    """tokens, support: the roots of a broadcast store, and shares of the steps below them, in tasks."""
    if o.prefix is not None and o.prefix not in store.names:
        return spark.createDataFrame([], FOUND)
    roots = range(len(store.names)) if o.prefix is None else [store.names.index(o.prefix)]
    parts = max(1, -(-4 * spark.sparkContext.defaultParallelism // max(1, len(roots)))) if o.max_items is None or o.max_items > 2 else 1
    units = [(r, k, parts) for k in range(parts) for r in roots]
    if not units:
        return spark.createDataFrame([], FOUND)
    shared = spark.sparkContext.broadcast((store, units))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, units = shared.value
        out = Found(store.names)
        branches = Branches(store, minsup, o, out)
        for batch in batches:
            for i in batch.column(0).to_pylist():
                branches.root(*units[i])
                yield from out.batches()

    tasks = min(len(units), 4 * spark.sparkContext.defaultParallelism)
    return written(spark.range(0, len(units), 1, tasks).mapInArrow(run, FOUND))


def mine_small(items: DataFrame, minsup: int, o: Options) -> DataFrame:
    """tokens, support of a database that was counted to fit: its events come to the driver as arrays and are broadcast."""
    rows = items.select(F.col("sid").cast("long").alias("sid"), F.col("pos").cast("int").alias("pos"), F.col("item").cast("string").alias("item")).toArrow()
    return mine_store(items.sparkSession, Store.read(rows, minsup), minsup, o)


def partner_patterns(positives: dict[Tokens, tuple[int, np.ndarray]], minsup: int, low: int, max_neg_size: int | None, unit: str) -> Iterator[tuple[Tokens, int]]:
    """Absence patterns of one root by set algebra on the sequence ids of its positive patterns: of each pattern of support low, inner elements that are no neighbours are negated, and the sequences of the partners go."""
    done: set[Tokens] = set()
    for full, (support, _) in positives.items():
        if support < low:
            continue
        inner = range(1, len(full) - 1)
        for mask in range(1, 1 << len(inner)):
            if mask & mask >> 1:
                continue
            negated = [k for k in inner if mask >> (k - 1) & 1]
            if max_neg_size is not None and max(len(full[k][1]) for k in negated) > max_neg_size:
                continue
            tokens = tuple((k in negated, x) for k, (_, x) in enumerate(full))
            if tokens in done:
                continue
            done.add(tokens)
            whole = positives[tuple(t for t in tokens if not t[0])][0]
            present = [(k, x) for k in negated for x in ([full[k][1]] if unit == "itemset" else [(i,) for i in full[k][1]])]
            partners = [positives[tuple((False, x if i == k else t[1]) for i, t in enumerate(tokens) if not t[0] or i == k)][1] for k, x in present]
            lost = len(partners[0]) if len(partners) == 1 else len(np.unique(np.concatenate(partners)))
            if whole - lost >= minsup:
                yield tokens, whole - lost


def mine_partner_small(items: DataFrame, minsup: int, low: int, max_items: int | None, max_neg_size: int | None, unit: str) -> DataFrame:
    """tokens, support by the partner miner of a database that was counted to fit: a root holds its patterns' positive parts and partners too, so roots are mined in different tasks."""
    rows = items.select(F.col("sid").cast("long").alias("sid"), F.col("pos").cast("int").alias("pos"), F.col("item").cast("string").alias("item")).toArrow()
    spark, least = items.sparkSession, min(low, minsup)
    store = Store.read(rows, least)
    if not store.names:
        return spark.createDataFrame([], FOUND)
    shared = spark.sparkContext.broadcast(store)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store = shared.value
        out = Found(store.names)
        for batch in batches:
            for root in batch.column(0).to_pylist():
                positives: dict[Tokens, tuple[int, np.ndarray]] = {}
                Branches(store, least, Options(max_items=max_items, negatives=False), lambda t, n, sids: positives.__setitem__(t, (n, sids)), with_sids=True).root(root)
                for tokens, (n, _) in positives.items():
                    if n >= minsup:
                        out(tokens, n)
                for tokens, n in partner_patterns(positives, minsup, low, max_neg_size, unit):
                    out(tokens, n)
                yield from out.batches()

    tasks = min(len(store.names), 4 * spark.sparkContext.defaultParallelism)
    return written(spark.range(0, len(store.names), 1, tasks).mapInArrow(run, FOUND))


#: What counter() returns.
COUNTED = "mean_len int, seed int, sigma int, maxgap int, ratio int, patterns long"


def counter(cells: list[tuple[int, int, int, int, int, int]]):
    """For the rows of one data set (mean_len, seed, sid, pos, item) the number of patterns of each of its cells: mean_len, seed, sigma in percent, maxgap (0: none), ratio (0: growth, otherwise the partner miner's percentage), the most items."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        long, seed = int(pdf["mean_len"].iloc[0]), int(pdf["seed"].iloc[0])
        rows = pa.table({"sid": pa.array(pdf["sid"]), "pos": pa.array(pdf["pos"]), "item": pa.array(pdf["item"])})
        n, out = pdf["sid"].nunique(), []
        for mean_len, of, sigma, gap, ratio, most in cells:
            if (mean_len, of) != (long, seed):
                continue
            minsup = max(1, -(-n * sigma // 100))
            low = max(1, -(-minsup * ratio // 100)) if ratio else minsup
            store = Store.read(rows, min(low, minsup))
            count = [0]

            def add(tokens: Tokens, support: int, _: np.ndarray | None, count=count) -> None:
                count[0] += 1

            for root in range(len(store.names)):
                if not ratio:
                    Branches(store, minsup, Options(maxgap=gap or None, max_items=most), add).root(root)
                    continue
                positives: dict[Tokens, tuple[int, np.ndarray]] = {}
                Branches(store, min(low, minsup), Options(max_items=most, negatives=False), lambda t, s, sids, p=positives: p.__setitem__(t, (s, sids)), with_sids=True).root(root)
                count[0] += sum(s >= minsup for s, _ in positives.values()) + sum(1 for _ in partner_patterns(positives, minsup, low, 1, "itemset"))
            out.append((long, seed, sigma, gap, ratio, count[0]))
        return pd.DataFrame(out, columns=["mean_len", "seed", "sigma", "maxgap", "ratio", "patterns"])

    return run


def mine_local(sequences: list[list[list[str]]], minsup: int, o: Options) -> dict[tuple[tuple[bool, tuple[str, ...]], ...], int]:
    """Tokens and supports of sequences in memory."""
    rows = [(k, j, x) for k, s in enumerate(sequences) for j, sets in enumerate(s, 1) for x in sets]
    table = pa.table({"sid": pa.array([r[0] for r in rows], pa.int64()), "pos": pa.array([r[1] for r in rows], pa.int32()), "item": pa.array([r[2] for r in rows], pa.string())})
    store, out = Store.read(table, minsup), {}
    names = store.names

    def found(tokens: Tokens, support: int, _: np.ndarray | None) -> None:
        out[tuple((n, tuple(names[i] for i in x)) for n, x in tokens)] = support

    branches = Branches(store, minsup, o, found)
    for r in range(len(names)) if o.prefix is None else [names.index(o.prefix)] if o.prefix in names else []:
        branches.root(r)
    return out


def root_sizes(items: DataFrame, minsup: int) -> DataFrame:
    """item, rows: the events of the sequences that hold the item, of each frequent one."""
    per = items.groupBy("sid").agg(F.count("*").alias("rows"))
    held = items.select("sid", "item").distinct().join(per, "sid")
    return held.groupBy("item").agg(F.sum("rows").alias("rows"), F.count("*").alias("s")).where(F.col("s") >= minsup).select("item", "rows")


def _mine_roots(items: DataFrame, minsup: int, o: Options, roots: DataFrame, n_roots: int, names: list[str]) -> DataFrame:
    """tokens, support: each of the given roots in one task, with the events of its sequences from its first place on. Thresholds are global, as a root's sequences are complete in its group; names are all frequent items, as also one that no sequence of the root holds can be absent."""
    spark = items.sparkSession
    kept = items.join(planner.small(spark.createDataFrame([(x,) for x in names], "item string"), len(names)), "item", "left_semi")
    first = kept.groupBy("sid", F.col("item").alias("root")).agg(F.min("pos").alias("first"))
    first = first.join(planner.small(roots.select(F.col("item").alias("root")), n_roots), "root", "left_semi")
    shipped = first.join(kept, "sid").where("pos >= first").select("root", "sid", "pos", "item")
    shared = spark.sparkContext.broadcast(names)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        names = shared.value
        code = {x: i for i, x in enumerate(names)}
        store = Store.of(pd.factorize(pdf["sid"])[0], pdf["pos"].to_numpy(), pdf["item"].map(code).to_numpy(), names)
        rows: list[tuple[Tokens, int]] = []
        Branches(store, minsup, o, lambda tokens, support, _: rows.append((tokens, support))).root(code[pdf["root"].iloc[0]])
        return pd.DataFrame({"tokens": [[{"neg": n, "items": [names[i] for i in x]} for n, x in t] for t, _ in rows], "support": [n for _, n in rows]})

    return shipped.groupBy("root").applyInPandas(run, FOUND)


def mine_hybrid(items: DataFrame, sigma: str | float | int, o: Options | None = None, local_rows: int | None = None) -> DataFrame:
    """Roots whose sequences fit a task depth-first, the others by the frontier engine, each with its root as prefix."""
    from .growth import mine

    o = o or Options()
    local_rows = planner.LOCAL_ROWS if local_rows is None else local_rows
    n = n_sequences(items)
    minsup = max(1, threshold(n, sigma))
    sizes = written(root_sizes(items, minsup))
    n_roots = sizes.count()
    if n_roots > planner.BROADCAST_ROWS or not able(o):
        return mine(items, minsup, o, sequences=n, engine="frontier")
    names = sorted(r[0] for r in sizes.select("item").collect())
    wanted = sizes if o.prefix is None else sizes.where(F.col("item") == o.prefix)
    fits = wanted.where(F.col("rows") <= local_rows)
    out = described(written(_mine_roots(items, minsup, o, fits, n_roots, names)))
    for r in wanted.where(F.col("rows") > local_rows).orderBy("item").select("item").collect():
        out = out.unionAll(mine(items, minsup, replace(o, prefix=r[0]), sequences=n, engine="frontier"))
    return out


def mine_by_root(items: DataFrame, sigma: str | float | int, o: Options | None = None) -> DataFrame:
    """Depth-first mining of every root that fits a task (LOCAL_ROWS events); larger ones go to the frontier engine."""
    return mine_hybrid(items, sigma, o)
