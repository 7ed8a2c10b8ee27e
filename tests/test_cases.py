import random

import pytest

from negseq.functions.pattern import parse
from negseq.functions.semantics import Constraints, Semantics
from negseq.operators import bit_engine

from . import brute
from .test_bits import large
from .test_growth import items_of


def test_case_packs_once(spark, monkeypatch):
    """Both miners of a case share one pass over the tables."""
    from negseq import workloads

    items, calls, pack = items_of(spark, brute.database(random.Random(13), "abc", 9)), [], bit_engine.pack
    monkeypatch.setattr(workloads.S, "basket_brand", lambda *_: items)
    monkeypatch.setattr(bit_engine, "pack", lambda x: calls.append(1) or pack(x))
    large(monkeypatch)
    assert {r["side"] for r in workloads.QUERIES["case_overlap"](spark, "").collect()} and len(calls) == 1
    workloads.QUERIES["case_missed"](spark, "").collect()
    assert len(calls) == 2


@pytest.mark.parametrize("name", ["mine_lminus_itemsets", "mine_partial_soft", "mine_partial_strict"])
def test_partial_packs_once(spark, monkeypatch, name):
    """The sets to be absent come from the packed sequences, and no second pass over the tables is made."""
    from pyspark.sql import functions as F

    from negseq import workloads

    db, passes = brute.database(random.Random(14), "abc", 12), spark.sparkContext.accumulator(0)
    seen = F.udf(lambda x: passes.add(1) or x, "string")
    items = items_of(spark, db).withColumn("item", seen("item"))
    monkeypatch.setattr(workloads.S, "basket_type", lambda *_: items)
    large(monkeypatch)
    got = {r["pattern"]: r["support"] for r in workloads.QUERIES[name](spark, "").collect()}
    assert any("!(a b)" in t for t in got) and passes.value == sum(len({*s}) for x in db for s in x)
    for t, n in got.items():
        assert n == sum(brute.holds(s, parse(t), Semantics("partial", "strict" if name.endswith("strict") else "soft"), Constraints(3)) for s in db), t


@pytest.mark.parametrize("name", ["endpoints", "mine_lminus_itemsets", "mine_partial_strict", "mine_two_item_negative", "real_basket_brand", "real_partner_basket_brand"])
def test_packing_exchanges_once(spark, monkeypatch, name):
    """Behind the join of the tables there is one exchange, by sequence: places, bits and rows of a sequence follow from it."""
    from negseq import workloads

    plans, written = [], bit_engine.written
    monkeypatch.setattr(bit_engine, "written", lambda df: plans.append(df._jdf.queryExecution().executedPlan().toString()) or written(df))
    large(monkeypatch)
    assert workloads.QUERIES[name](spark, "/root/testdata/sf0.001").count()
    assert plans[0].count("Exchange hashpartitioning(sid") == 1 and "Exchange hashpartitioning(o_custkey" not in plans[0]


def test_orders_travel_as_bits(spark, tmp_path):
    """The lines of an order meet before they are exchanged; alphabets of several words, an unknown item, orders of one day."""
    from negseq.operators import sequences as S

    rng, d = random.Random(15), str(tmp_path)
    names = [None, *(f"type {k:03d}" for k in range(149))]
    orders = [(o, rng.randrange(4), f"2024-01-0{rng.randrange(1, 6)} 00:00:00") for o in range(40)]
    lines = [(rng.randrange(42), rng.randrange(160)) for _ in range(400)]
    spark.createDataFrame(list(enumerate(names)), "p_partkey long, p_type string").write.parquet(f"{d}/part.parquet")
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long, day string").selectExpr("o_orderkey", "o_custkey", "timestamp(day) AS o_orderdate").write.parquet(f"{d}/orders.parquet")
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").write.parquet(f"{d}/lineitem.parquet")
    rows = {(c, day, names[p]) for o, c, day in orders for k, p in lines if k == o and p < len(names)}
    days = {c: sorted({day for x, day, _ in rows if x == c}) for c in range(4)}
    got = S.basket_type(spark, d)
    key = lambda x: (x[0], x[1], x[2] or "")
    assert sorted(map(tuple, got.collect()), key=key) == sorted(((c, days[c].index(day) + 1, x) for c, day, x in rows), key=key)
    assert "partial_bit_or" in got._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("group", [64, 256])
def test_lines_are_exchanged_by_order_only(spark, tmp_path, monkeypatch, group):
    """However large the parts, no line is exchanged for its part, and the lines that met are not exchanged again for the join. Keys below zero, far apart, twice and null; more items than a row holds."""
    from negseq.operators import sequences as S

    rng, d = random.Random(17), str(tmp_path)
    monkeypatch.setattr(S, "GROUP", group, raising=False)
    keys = [*range(-70, 70), 10**12, 10**12 + 1, 5, 5, -1, None]
    parts = [(k, rng.choice([None, *(f"brand {x:03d}" for x in range(130))])) for k in keys]
    orders = [(o, rng.randrange(4), f"2024-01-0{rng.randrange(1, 6)} 00:00:00") for o in range(40)]
    lines = [(rng.randrange(42), rng.choice([*keys, 77, 128])) for _ in range(600)]
    spark.createDataFrame(parts, "p_partkey long, p_brand string").write.parquet(f"{d}/part.parquet")
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long, day string").selectExpr("o_orderkey", "o_custkey", "timestamp(day) AS o_orderdate").write.parquet(f"{d}/orders.parquet")
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").write.parquet(f"{d}/lineitem.parquet")
    rows = {(c, day, x) for o, c, day in orders for k, p in lines if k == o and p is not None for q, x in parts if p == q}
    days = {c: sorted({day for x, day, _ in rows if x == c}) for c in range(4)}
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        got = S.basket_brand(spark, d)
        key = lambda x: (x[0], x[1], x[2] or "")
        assert sorted(map(tuple, got.collect()), key=key) == sorted(((c, days[c].index(day) + 1, x) for c, day, x in rows), key=key)
        plan = got._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[-1]
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert "hashpartitioning(l_partkey" not in plan and "hashpartitioning(_item" not in plan
    assert group < 130 or plan.count("Exchange hashpartitioning(l_orderkey") == 1
