import random

import numpy as np
import pytest

from negseq.functions.pattern import parse
from negseq.functions.semantics import Constraints, Semantics
from negseq.operators import baselines, bit_engine, growth, local_engine
from negseq.operators.growth import Options

from . import brute
from .test_growth import found, items_of, read


def unpacked(x: np.ndarray) -> set[int]:
    return {64 * w + i for w in range(len(x)) for i in range(64) if int(x[w, 0]) >> i & 1}


def test_reach_is_the_definition():
    rng = random.Random(8)
    for _ in range(300):
        wide, gap = rng.choice([1, 2, 3]), rng.choice([None, 1, 3, 10, 70])
        one = lambda share: {i for i in range(64 * wide) if rng.random() < share}
        ends, blocked = one(rng.choice([0.02, 0.3])), one(rng.choice([0.02, 0.3, 0.9])) if rng.random() < 0.8 else None
        bits = lambda at: np.array([[sum(1 << (i % 64) for i in at if i // 64 == w)] for w in range(wide)], np.uint64)
        want = {j for j in range(64 * wide) if any(i < j and (gap is None or j - i <= gap) and not (blocked and any(i < b < j for b in blocked)) for i in ends)}
        assert unpacked(bit_engine.reach(bits(ends), gap, None if blocked is None else bits(blocked))) == want


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_bits_are_local(spark, seed):
    """Sequences of more than one word too."""
    rng = random.Random(seed)
    db = brute.database(rng, "abcd", 8)
    db[0] = [rng.choice(rng.choice(db[1:])) if i % 9 == 0 else [] for i in range(150)]
    o = Options(maxgap=rng.choice([None, 9]), max_items=3 if seed > 1 else 4, max_neg_size=2, surround=["off", "checked", "printed"][seed - 1], redundancy=[None, None, "drop_last"][seed - 1])
    want = found(local_engine.mine_local(db, 3, o))
    assert sum("!" in t for t in want) > 5 and read(growth.mine(items_of(spark, db), 3, o, engine="bits")) == want


def test_bits_in_parts(spark, monkeypatch):
    """Small chunks, and the nodes of a level in several passes."""
    monkeypatch.setattr(bit_engine, "COUNTERS", 30)
    monkeypatch.setattr(bit_engine, "CHUNK", 2)
    db = brute.database(random.Random(7), "abc", 9)
    assert read(growth.mine(items_of(spark, db), 3, Options(maxgap=2), engine="bits")) == baselines.mine_exhaustive(db, 3, 3, c=Constraints(2), max_neg_size=1)


@pytest.mark.parametrize("ratio", [0.2, 0.7, 1.0])
def test_partner_on_bits(spark, ratio):
    items = items_of(spark, brute.database(random.Random(6), "abcd", 12))
    want = read(baselines.mine_partner(items, 5, ratio))
    assert any("!" in t for t in want) and read(baselines.mine_partner(items, 5, ratio, engine="bits")) == want
    with pytest.raises(ValueError):
        baselines.mine_partner(items, 5, ratio, max_items=5, engine="bits")


def large(monkeypatch):
    """Every database counts as too large for a task, and no frontier may be made."""
    for module in (growth, baselines):
        monkeypatch.setattr(module, "LOCAL_ROWS", 0)
    monkeypatch.setattr(growth.Miner, "run", lambda *a, **k: pytest.fail("a frontier"))


@pytest.mark.parametrize("embedding", ["soft", "strict"])
def test_large_partial_makes_no_frontier(spark, monkeypatch, embedding):
    large(monkeypatch)
    db = brute.database(random.Random(12), "abc", 9)
    lminus = spark.createDataFrame([(["a", "b"],), (["c"],), (["b", "zz"],)], "items array<string>")
    got = read(growth.mine(items_of(spark, db), 3, Options(max_items=4, max_neg_size=2, max_pos_items=2, max_itemsets=2, non_inclusion="partial", embedding=embedding), lminus))
    names = {t for t in got if "!" in t}
    assert any("(a b)" in t for t in names) and any("(b zz)" in t for t in names)
    for t, n in got.items():
        p = parse(t)
        assert n == sum(brute.holds(s, p, Semantics("partial", embedding), Constraints()) for s in db), t


def test_large_baskets_make_no_frontier(spark, monkeypatch):
    large(monkeypatch)
    db = brute.database(random.Random(13), "abc", 9)
    items = items_of(spark, db)
    assert read(growth.mine(items, 3, Options(maxgap=2))) == baselines.mine_exhaustive(db, 3, 3, c=Constraints(2), max_neg_size=1)
    assert len(read(baselines.mine_partner(items, 3, 0.1))) > 20


def test_edges_of_sequences():
    bits = np.array([[0, 1 << 5 | 1 << 63, 0, 2], [0, 0, 1 << 63 | 1, 1]], np.uint64)
    assert bit_engine._edge(bits).tolist() == [128, 5, 64, 1] and bit_engine._edge(bits, last=True).tolist() == [-1, 63, 127, 64]


def test_steps_without_gap_read_edges(spark, monkeypatch):
    """Of what follows without a gap, places are not compared word by word; what cannot compose is not counted."""
    rng = random.Random(16)
    db = [[[rng.choice("abcd")] for _ in range(rng.choice([3, 70, 140]))] for _ in range(8)]
    want = found(local_engine.mine_local(db, 3, Options(negatives=False)))
    monkeypatch.setattr(bit_engine.Chunk, "tally", None)
    assert len(want) > 50 and read(growth.mine(items_of(spark, db), 3, Options(negatives=False), engine="bits")) == want
