import pytest

from negseq.functions.pattern import PatternError, classic_subpattern, parse, precedes, quote, validate


@pytest.mark.parametrize("text", ["a", "a !c (b d)", "(a b) !(c d) e", "`4-NOT SPECIFIED` !`a!` b", "a !e b (c e) !(b d) a"])
def test_round_trip(text):
    assert parse(text).text == text


def test_canonical():
    assert parse("a !(d c c) ( f  e )").text == "a !(c d) (e f)"
    assert parse(quote("a `b`")).positives == (("a `b`",),)


@pytest.mark.parametrize("text", ["!b d", "a !b", "a !b !(c d) e", "a !!b c", "a !(b !c) d", "a () b", "a !() b", "", "a (b", "a b)", "a (b (c))"])
def test_rejected(text):
    assert validate(text)
    with pytest.raises(PatternError):
        parse(text)


def test_parts():
    p = parse("a !b c !(d e) f")
    assert p.positive_part().text == "a c f"
    assert p.partner().text == "a b c (d e) f"
    assert [x.text for x in p.single_partners()] == ["a b c f", "a c (d e) f"]
    assert [x.text for x in p.single_partners("item")] == ["a b c f", "a c d f", "a c e f"]
    assert p.stats == {"n_items": 6, "n_itemsets": 3, "n_neg": 2, "max_neg_size": 2}


def test_order():
    assert precedes(parse("a b"), parse("a !c b"), strict=True)
    assert precedes(parse("a !c b"), parse("a !(c d) (b e) f"))
    assert not precedes(parse("a !c b"), parse("a b"))
    assert not precedes(parse("b !c a"), parse("b !c d a"))
    assert classic_subpattern(parse("b !c a"), parse("b !c d a"))
    assert precedes(parse("a"), parse("a")) and not precedes(parse("a"), parse("a"), strict=True)


def test_columns_agree(spark):
    from pyspark.sql import functions as F

    from negseq.functions.pattern import is_pattern, positive_part, positive_partner, precedes_column, stats, text_of
    from negseq.operators.postprocess import from_texts

    texts = ["a", "a b", "a !c b", "a !(c d) b", "a !(c d) (b e) f", "b !c d a", "b !c a", "(a b) c", "`x y` !z a"]
    df = from_texts(spark.range(1), texts)
    for r in df.select("pattern", "tokens", text_of(positive_part("tokens")).alias("pos"), text_of(positive_partner("tokens")).alias("partner"), stats("tokens").alias("s"), is_pattern("tokens").alias("ok")).collect():
        p = parse(r["pattern"])
        assert (r["pos"], r["partner"], r["s"].asDict(), r["ok"]) == (p.positive_part().text, p.partner().text, p.stats, True)
    right = df.select(F.col("pattern").alias("q"), F.col("tokens").alias("u"))
    for r in df.crossJoin(right).select("pattern", "q", precedes_column(F.col("tokens"), F.col("u")).alias("x")).collect():
        assert r["x"] == precedes(parse(r["pattern"]), parse(r["q"])), (r["pattern"], r["q"])
