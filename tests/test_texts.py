import random

import pytest

from negseq.functions.pattern import parse
from negseq.functions.semantics import GROWTH, Constraints
from negseq.operators import baselines, bit_engine, postprocess
from negseq.operators import sequences as S

from . import brute
from .test_growth import items_of, read


def test_contrast_of_items_is_the_definition(spark, monkeypatch):
    """Only places of the patterns' items are gathered, also in sequences of many words of bits; a sequence without these items counts."""
    rng = random.Random(21)
    db = brute.database(rng, "abcdef", 30)
    db[0] = [[rng.choice("abcdef")] if i % 7 == 0 else ["f"] for i in range(300)]
    db[1] = [["f"]]
    items = items_of(spark, db)
    sids = sorted(r[0] for r in items.select("sid").distinct().collect())
    classes = spark.createDataFrame([(s, k % 2) for k, s in enumerate(sids)], "sid long, class long")
    patterns, c = ["a", "a !c b", "(a b) !c a", "a !(b c) d", "b a"], Constraints(4)
    monkeypatch.setattr(S, "nested", lambda *_: pytest.fail("all items are gathered"))
    got = {r["pattern"]: tuple(r)[1:] for r in postprocess.contrast_items(items, classes, patterns, 4).collect()}
    n = [len(sids[0::2]), len(sids[1::2])]
    for p in map(parse, patterns):
        held = [sum(brute.holds(s, p, GROWTH, c) for s in db[k::2]) for k in (0, 1)]
        rate = None if not held[0] else round(held[1] * n[0] / (held[0] * n[1]), 6)
        assert got[p.text] == (held[1], held[0], rate), p.text


def test_contrast_quality_gathers_named_items_only(spark, monkeypatch):
    from negseq import workloads

    monkeypatch.setattr(workloads.S, "nested", lambda *_: pytest.fail("all items are gathered"))
    assert workloads.QUERIES["contrast_quality"](spark, "/root/testdata/sf0.001").count() == 4


def test_partner_words_packs_frequent_items_only(spark, monkeypatch):
    from negseq import workloads

    db = [[["a"], *([["c"]] if k < 8 else []), ["b"], [f"rare{k}"]] for k in range(20)] + [[["lone"]]]
    items, kept, pack = items_of(spark, db), [], bit_engine.pack
    want = read(baselines.mine_partner(items, "0.5", 0.7))
    monkeypatch.setattr(bit_engine, "pack", lambda x: kept.extend(r[0] for r in x.select("item").distinct().collect()) or pack(x))
    monkeypatch.setattr(workloads.S, "VIEWS", {**S.VIEWS, "words": lambda *_: items})
    got = {r["pattern"]: r["support"] for r in workloads.QUERIES["real_partner_words"](spark, "").collect()}
    assert got == want and any("!" in t for t in want) and set(kept) == set("abc")
