import random

import pytest

from negseq.functions.pattern import parse
from negseq.functions.semantics import ALL, FREE, Constraints, Semantics, embeddings, occurs
from negseq.functions.semantics import holds as by_embeddings
from negseq.operators import matching
from negseq.operators.baselines import language

from . import brute

INCLUSION = [[["b", "c"], ["f"], ["a"]], [["b", "c"], ["c", "f"], ["a"]], [["b", "c"], ["d", "f"], ["a"]], [["b", "c"], ["e", "f"], ["a"]], [["b", "c"], ["c", "d", "e", "f"], ["a"]]]
ABSENCE = [[["a"], ["c"], ["b"], ["e"], ["d"]], [["a"], ["b", "c"], ["e"], ["d"]], [["a"], ["b"], ["e"], ["d"]], [["a"], ["e"], ["d"]]]


@pytest.mark.parametrize(("text", "partial", "total"), [("b !c a", {1, 3, 4}, {1, 3, 4}), ("b !(c d) a", {1, 2, 3, 4}, {1, 4}), ("b !(c d e) a", {1, 2, 3, 4}, {1}), ("b !(c d e g) a", {1, 2, 3, 4, 5}, {1})])
def test_inclusion(text, partial, total):
    got = lambda kind: {i for i, s in enumerate(INCLUSION, 1) if occurs(s, parse(text), Semantics(kind))}
    assert (got("partial"), got("total")) == (partial, total)


def test_absence():
    p = parse("a !(b c) d")
    got = lambda *s: {i for i, x in enumerate(ABSENCE, 1) if occurs(x, p, Semantics(*s))}
    assert got("partial", "soft") == {1, 3, 4}
    assert got("partial", "strict") == {3, 4}
    assert got("total", "soft") == got("total", "strict") == {4}


def test_occurrence():
    s = [["a"], ["b"], ["c"], ["a"], ["d"], ["e"], ["b"], ["d"]]
    assert list(embeddings(s, parse("a b d"))) == [(1, 2, 5), (1, 2, 8), (1, 7, 8), (4, 7, 8)]
    assert occurs(s, parse("a b !c d")) and not occurs(s, parse("a b !c d"), Semantics(occurrence="strict"))


def test_gaps_tell_equal_patterns_apart():
    s = [["a"], ["b"], ["b"], ["x"], ["c"]]
    assert occurs(s, parse("a !b b c")) == occurs(s, parse("a b !b c"))
    assert not occurs(s, parse("a !b b c"), c=Constraints(2)) and occurs(s, parse("a b !b c"), c=Constraints(2))


def test_constraints_are_checked():
    for bad in ({"maxgap": 0}, {"maxspan": -1}):
        with pytest.raises(ValueError):
            Constraints(**bad)
    with pytest.raises(ValueError):
        Semantics("none")


def test_fold_is_brute_force():
    rng, patterns = random.Random(1), language(list("abc"), 4, 2)
    for _ in range(250):
        s = brute.database(rng, "abc", 1)[0]
        p, c = rng.choice(patterns), Constraints(rng.choice([None, 1, 2, 3]), rng.choice([None, 2, 4]))
        for sem in ALL:
            want = brute.holds(s, p, sem, c)
            assert occurs(s, p, sem, c) == by_embeddings(s, p, sem, c) == want, (s, p.text, sem, c)


def test_laws():
    rng, patterns = random.Random(2), language(list("abc"), 4, 2)
    for _ in range(300):
        s, p = brute.database(rng, "abc", 1)[0], rng.choice(patterns)
        has = {x: occurs(s, p, x) for x in ALL}
        for o in ("soft", "strict"):
            assert has[Semantics("total", "soft", o)] == has[Semantics("total", "strict", o)]
            assert not has[Semantics("total", "soft", o)] or has[Semantics("partial", "strict", o)]
            assert not has[Semantics("partial", "strict", o)] or has[Semantics("partial", "soft", o)]
        for a in ("total", "partial"):
            for e in ("soft", "strict"):
                assert not has[Semantics(a, e, "strict")] or has[Semantics(a, e, "soft")]
        # without gaps, set algebra over partners is strict occurrence
        positive = occurs(s, p.positive_part())
        for unit, sem in (("itemset", Semantics("partial", "soft", "strict")), ("item", Semantics("total", "soft", "strict"))):
            assert occurs(s, p, sem) == (positive and not any(occurs(s, q) for q in p.single_partners(unit)))


def test_columns_are_the_fold(spark):
    rng = random.Random(3)
    db = brute.database(rng, "abc", 12) + [[[], ["a"], []], [["a", "b"]]]
    df = spark.createDataFrame(list(enumerate(db)), "sid long, itemsets array<array<string>>")
    patterns = [parse(x) for x in ("a", "a !c b", "a !(b c) a", "(a b) !c b !a c", "a b !(a c) b")]
    for c in (FREE, Constraints(2), Constraints(None, 3)):
        flags = df.select("sid", *(matching.occurs("itemsets", p, sem, c).alias(f"x{i}_{k}") for i, p in enumerate(patterns) for k, sem in enumerate(ALL)))
        for r in flags.collect():
            for i, p in enumerate(patterns):
                for k, sem in enumerate(ALL):
                    assert r[f"x{i}_{k}"] == occurs(db[r["sid"]], p, sem, c), (db[r["sid"]], p.text, sem, c)


def test_matching_has_no_python(spark):
    df = spark.createDataFrame([(1, [["a"]])], "sid long, itemsets array<array<string>>")
    plan = df.where(matching.occurs("itemsets", "a !c b"))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Exchange" not in plan
