import random

import numpy as np
import pytest

from negseq.functions.pattern import Element, Pattern
from negseq.functions.semantics import Constraints, Semantics
from negseq.operators import baselines, growth, local_engine
from negseq.operators import sequences as S
from negseq.operators.growth import Options

from . import brute

EXAMPLE = [[["a"], ["c"], ["b"], ["e"], ["d"]], [["a"], ["b", "c"], ["e"]], [["a"], ["b"], ["e"], ["d"]], [["a"], ["e"], ["d"], ["f"]]]


def found(rows):
    """Supports by text of a dict from tokens."""
    out = {Pattern(tuple(Element(n, x) for n, x in t)).text: s for t, s in rows.items()}
    assert len(out) == len(rows)
    return out


def items_of(spark, db):
    return S.exploded(spark.createDataFrame(list(enumerate(db)), "sid long, itemsets array<array<string>>"))


@pytest.mark.parametrize(("size", "surround", "count"), [(1, "off", 385), (1, "checked", 145), (2, "off", 3910), (2, "checked", 413), (None, "checked", 515)])
def test_sizes_of_the_example(size, surround, count):
    got = found(local_engine.mine_local(EXAMPLE, 2, Options(max_items=None, max_neg_size=size, surround=surround)))
    assert len(got) == count and sum("!" not in t for t in got) == 19


def test_supports_of_the_example():
    got = found(local_engine.mine_local(EXAMPLE, 2, Options(max_items=4, max_neg_size=2)))
    want = {"a": 4, "a e": 4, "a e d": 3, "a !c e": 2, "a !(c d) e": 2, "a !d e": 4, "a !d e d": 3, "a !c e d": 2, "a d": 3}
    assert {t: got.get(t) for t in want} == want
    assert not {"a !b e", "a (b c)"} & set(got)


def read(df):
    rows = df.select("pattern", "support").collect()
    out = {r["pattern"]: r["support"] for r in rows}
    assert len(out) == len(rows)
    return out


def test_local_is_exhaustive():
    rng = random.Random(5)
    for _ in range(25):
        db, minsup, gap = brute.database(rng), rng.choice([2, 3]), rng.choice([None, 1, 2, 3])
        want = baselines.mine_exhaustive(db, minsup, 4, c=Constraints(gap), max_neg_size=2)
        assert found(local_engine.mine_local(db, minsup, Options(maxgap=gap, max_items=4, max_neg_size=2))) == want


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_frontier_is_local(spark, seed):
    rng = random.Random(seed)
    db = brute.database(rng, "abc", 6)
    o = Options(maxgap=rng.choice([None, 2]), max_items=4, max_neg_size=2, surround=["off", "checked", "printed"][seed - 1], redundancy=[None, None, "drop_last"][seed - 1])
    items = items_of(spark, db)
    want = found(local_engine.mine_local(db, 2, o))
    assert read(growth.mine(items, 2, o, engine="frontier")) == want and read(growth.mine(items, 2, o)) == want


def test_frontier_with_maxspan(spark):
    db = brute.database(random.Random(2), "abc", 6)
    got = read(growth.mine(items_of(spark, db), 2, Options(maxspan=3, maxgap=2, max_items=4, max_neg_size=1)))
    assert got == baselines.mine_exhaustive(db, 2, 4, c=Constraints(2, 3), max_neg_size=1)


def test_violated_two_ways():
    """Few events in the windows, or many: both give the same rows."""
    rng = random.Random(31)
    for _ in range(20):
        db = [[[rng.choice("abc")] for _ in range(40)] for _ in range(6)]
        rows = [(k, j, x) for k, s in enumerate(db) for j, y in enumerate(s, 1) for x in y]
        sid, pos, item = (np.array(x) for x in zip(*rows, strict=True))
        store = local_engine.Store.of(sid, pos, np.searchsorted(["a", "b", "c"], item), ["a", "b", "c"])
        both = local_engine.Branches(store, 1, Options(), lambda *_: None)
        ends = np.sort(rng.sample(sorted(store.key), 30))
        base = store.base[np.searchsorted(store.key, ends)]
        before = np.maximum(base, ends - rng.choice([3, 40]))
        got = {q: sorted(r) for q, r in both.violated(before, ends)}
        want = {}
        for i, (a, b) in enumerate(zip(before, ends, strict=True)):
            for q in {int(store.item[k]) for k in range(len(store.key)) if a < store.key[k] < b}:
                want.setdefault(q, []).append(i)
        assert got == want


def test_engines_agree(spark):
    db = brute.database(random.Random(9), "abcd", 8)
    items, o = items_of(spark, db), Options(maxgap=3)
    ours = read(growth.mine(items, "0.5", o, engine="frontier"))
    assert ours == read(growth.mine(items, "0.5", o)) == read(local_engine.mine_by_root(items, "0.5", o))
    # some roots are too large for a task
    sizes = sorted(r["rows"] for r in local_engine.root_sizes(items, 4).collect())
    assert ours == read(local_engine.mine_hybrid(items, "0.5", o, local_rows=sizes[len(sizes) // 2] - 1))
    prefix = Options(maxgap=3, prefix="b")
    assert read(growth.mine(items, "0.5", prefix)) == read(local_engine.mine_by_root(items, "0.5", prefix)) == read(growth.mine(items, "0.5", prefix, engine="frontier"))
    level = baselines.mine_levelwise(S.nested(items), "0.5", c=Constraints(3))
    assert ours == read(level)


@pytest.mark.parametrize("unit", ["itemset", "item"])
def test_partner_engines_agree(spark, unit):
    items = items_of(spark, brute.database(random.Random(12), "abcd", 10))
    run = lambda engine: read(baselines.mine_partner(items, "0.4", 0.5, max_items=5, max_neg_size=2, unit=unit, engine=engine))
    assert run("auto") == run("frontier") and any(t.count("!") == 2 for t in run("auto"))


def test_partner_is_strict(spark):
    db = brute.database(random.Random(11), "abc", 8)
    items = items_of(spark, db)
    got = {r["pattern"]: r["support"] for r in baselines.mine_partner(items, 3, 0.01, max_items=3).select("pattern", "support").collect()}
    want = baselines.mine_exhaustive(db, 3, 3, Semantics("partial", "soft", "strict"), max_neg_size=1)
    # an absence that is never contradicted has no positive partner and stays unknown
    known = {t: n for t, n in want.items() if "!" not in t or any(brute.holds(s, baselines.parse(t).partner(), Semantics(), Constraints()) for s in db)}
    assert got == known
    with pytest.raises(ValueError):
        baselines.mine_partner(items, 3, maxgap=2)


def test_thresholds():
    assert growth.threshold(150, "0.5") == 75 and growth.threshold(1500, "0.143") == 215 and growth.threshold(10, "0.3") == 3 and growth.threshold(7, 3) == 3


def test_edges(spark):
    empty = spark.createDataFrame([], "sid long, pos int, item string")
    assert growth.mine(empty, 1, Options()).count() == 0
    one = items_of(spark, [[["b", "a", "a"], None, ["c", None]]])
    got = {r["pattern"] for r in growth.mine(one, 1, Options(maxgap=1)).collect()}
    assert "(a b)" in got and "a c" not in got and "c" in got
    assert growth.mine(one, 2, Options()).count() == 0
    assert {r["pattern"] for r in growth.mine(items_of(spark, [[["x y"], ["a!"]]]), 1, Options(maxspan=0)).collect()} == {"`x y`", "`a!`"}
    rows = spark.createDataFrame([(1, 1, "a"), (1, 1, "b"), (None, 1, "c"), (1, None, "d"), (1, 2, None), (1, 3, "e")], "s long, o int, i string")
    assert sorted(map(tuple, S.build_sequences(rows, "s", ["o"], "i").collect())) == [(1, 1, "a"), (1, 1, "b"), (1, 2, "e")]
    assert S.build_sequences(rows, "s", ["o", "i"], "i", "rank").count() == 3


def test_partitions_do_not_matter(spark):
    db = brute.database(random.Random(13), "abc", 8)
    items = items_of(spark, db)
    read = lambda df: sorted((r["pattern"], r["support"]) for r in df.collect())
    assert read(growth.mine(items.coalesce(1), 3, Options(maxgap=2))) == read(growth.mine(items.repartition(7), 3, Options(maxgap=2)))


def test_extension_joins_do_not_shuffle_the_store(spark):
    db = brute.database(random.Random(17), "abc", 8)
    miner = growth.Miner(items_of(spark, db), 2, Options())
    plan = miner.store._jdf.queryExecution().executedPlan().toString()
    assert "InMemoryTableScan" in plan


@pytest.mark.parametrize(("gap", "span", "size"), [(None, None, 2), (2, None, 1), (3, 4, 2)])
def test_strict_is_exhaustive(spark, gap, span, size):
    """Any number of absences, in several gaps."""
    db = brute.database(random.Random(19), "abc", 9)
    got = read(baselines.mine_strict(items_of(spark, db), 3, Options(maxgap=gap, maxspan=span, max_items=5, max_neg_size=size)))
    want = baselines.mine_exhaustive(db, 3, 5, Semantics("total", "soft", "strict"), Constraints(gap, span), max_neg_size=size)
    assert got == want and any(t.count("!") == 2 for t in want)
