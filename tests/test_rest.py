import random

import pytest

from negseq.functions.pattern import parse
from negseq.functions.semantics import Constraints, embeddings, first_violation
from negseq.functions.semantics import GROWTH
from negseq.operators import generator, growth, measures, postprocess
from negseq.operators import sequences as S
from negseq.operators.growth import Options
from negseq.sources import sequence_text
from negseq.streaming.monitor import Tracker

from . import brute


def test_tracker_is_batch():
    rng = random.Random(4)
    patterns = [parse(x) for x in ("a !c b", "a b", "(a b) !a c !b a", "a !(b c) a")]
    for c in (Constraints(), Constraints(2), Constraints(None, 3), Constraints(2, 3)):
        for s in brute.database(rng, "abc", 20):
            tracker = Tracker(patterns, c)
            got = {(p, i) for i, items in enumerate(s, 1) for p in tracker.step(set(items))}
            want = {(p.text, e[-1]) for p in patterns for e in embeddings(s, p, c) if first_violation(s, p, e, GROWTH) is None}
            assert got == want, (s, c)


def test_replay_is_batch(spark, tmp_path):
    """Every completion comes out, also those of the last hour."""
    from datetime import datetime, timedelta

    from negseq.streaming.monitor import replay

    rng, rows, want = random.Random(9), [], set()
    patterns, c = [parse("a !c b"), parse("a b")], Constraints(3)
    for sid in range(6):
        at = sorted(rng.sample(range(0, 8 * 3600, 60), 12))
        s = [[rng.choice("abc")] for _ in at]
        rows += [(sid, datetime(2024, 1, 1) + timedelta(seconds=t), x[0]) for t, x in zip(at, s, strict=True)]
        want |= {(sid, p.text, e[-1]) for p in patterns for e in embeddings(s, p, c) if first_violation(s, p, e, GROWTH) is None}
    rng.shuffle(rows)
    got = replay(spark.createDataFrame(rows, "sid long, at timestamp, item string"), [p.text for p in patterns], c, path=str(tmp_path)).collect()
    assert len(got) == len(want) and {(r["sid"], r["pattern"], r["position"]) for r in got} == want


def test_tracker_state_survives_json():
    import json

    p = [parse("a !c b")]
    t = Tracker(p, Constraints())
    t.step({"a"})
    assert Tracker(p, Constraints(), json.loads(json.dumps(t.saved()))).step({"b"}) == ["a !c b"]


def test_sequence_text(spark, tmp_path):
    line = "1 3 -1 2 -1 -1 5 -2"
    assert sequence_text.parse_line(line) == [["1", "3"], ["2"], [], ["5"]]
    df = spark.createDataFrame([(line,), ("7 -1 -2",), ("4",)], "line string")
    from pyspark.sql import functions as F

    got = [r[0] for r in df.select(sequence_text.parse_column(F.col("line"))).collect()]
    assert got == [sequence_text.parse_line(x) for x in (line, "7 -1 -2", "4")]
    rows = spark.createDataFrame([(1, [["1"], ["2", "3"]]), (2, [["9"]])], "sid long, itemsets array<array<string>>")
    sequence_text.write(rows, str(tmp_path / "a"))
    assert sorted(r["itemsets"] for r in sequence_text.read(spark, str(tmp_path / "a")).collect()) == [[["1"], ["2", "3"]], [["9"]]]
    sequence_text.register(spark)
    rows.select("itemsets").write.format("seqtext").mode("append").save(str(tmp_path / "b"))
    assert sorted(r["itemsets"] for r in spark.read.format("seqtext").load(str(tmp_path / "b")).collect()) == [[["1"], ["2", "3"]], [["9"]]]


def test_generator(spark):
    a, truth = generator.generate(spark, 200, seed=3)
    b, _ = generator.generate(spark, 200, seed=3)
    assert a.repartition(5).exceptAll(b).count() == 0
    from negseq.operators.matching import support

    planted = {r["pattern"]: r["planted"] for r in truth.collect()}
    got = {r["pattern"]: r["support"] for r in support(a, list(planted)).collect()}
    # later plantings may overwrite some of the earlier ones
    assert all(got[p] >= 0.6 * n for p, n in planted.items())
    profile = measures.profile(S.exploded(a)).first()
    assert profile["sequences"] == 200 and 17 < profile["mean_len"] < 23 and profile["alphabet"] == 20


def test_thresholds_follow_the_data(spark, tmp_path, monkeypatch):
    from negseq import workloads

    d = str(tmp_path)
    rows = [(u, f"2024-01-0{k} 00:00:00", x) for u in range(4) for k, x in enumerate(("click", "refund", "signup"), 1)]
    spark.createDataFrame(rows, "user_id long, ts string, event_type string").selectExpr("user_id", "timestamp(ts) AS ts", "event_type").write.parquet(f"{d}/events.parquet")
    got = workloads.QUERIES["semantics_counts"](spark, d).collect()
    assert got and all((r["frequent"], r["total"]) == (1, 4) for r in got)
    used = {}
    monkeypatch.setattr(workloads.growth, "mine", lambda items, sigma, options: used.setdefault(options.negatives, sigma))
    monkeypatch.setattr(workloads.baselines, "mine_partner", lambda items, sigma, ratio: None)
    monkeypatch.setattr(workloads.measures, "missed_by_partner", lambda a, b, c, low: low)
    for n, low in ((10, 4), (250, 88), (2500, 875)):
        spark.range(n).selectExpr("id AS page_id", "'<p>' AS html").write.mode("overwrite").parquet(f"{d}/pages.parquet")
        assert workloads.QUERIES["partner_missed"](spark, d) == low


def test_time_limit(spark):
    import time

    from pyspark.sql import functions as F

    slow = F.udf(lambda x: time.sleep(0.2) or x, "long")
    got = measures.timed(spark, lambda: spark.range(2000, numPartitions=4).select(slow("id").alias("x")).where("x >= 0"), 2)
    assert got["status"] == "timeout" and got["rows"] is None
    assert measures.timed(spark, lambda: spark.range(10))["rows"] == 10


def test_merge_refuses_gaps(spark):
    with pytest.raises(ValueError):
        postprocess.merge_redundant(postprocess.from_texts(spark.range(1), ["a"]), Constraints(2))


def test_entry_without_llm(tmp_path):
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    repo = Path(__file__).resolve().parent.parent
    shutil.copytree(repo / "negseq", tmp_path / "negseq", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(repo / "__spark_entry__.py", tmp_path)
    said = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()), any(k.startswith('op1') for k in e.queries()))"], cwd=tmp_path, capture_output=True, text=True)
    n, m, has = said.stdout.split()[-3:]
    assert int(n) > 90 and int(m) > 90 and has == "False", said.stderr


def test_first_embedding_of_nulls():
    import pandas as pd

    from negseq.functions.surface import first_embedding

    got = first_embedding(pd.Series([[["a"], None, ["b"]], None, [["a"]], [["a"], ["c"], ["b"]]]), pd.Series(["a !c b", "a", None, "a !c b"]))
    assert [None if x is None else list(x) for x in got] == [[1, 3], None, None, None]


def test_patterns_and_trees_are_kept(spark, tmp_path):
    from negseq.sources import tables

    items = spark.createDataFrame([(1, 1, "a"), (1, 2, "b"), (2, 1, "a"), (2, 3, "b")], "sid long, pos int, item string")
    found = growth.mine(items, 2, Options())
    tables.save_patterns(found, str(tmp_path / "p"))
    assert tables.load_patterns(spark, str(tmp_path / "p")).count() == found.count() == 5
    tree = tables.tree_text(growth.trace(items, 2, Options()))
    assert '"a" -> "a b"' in tree and '"a b" -> "a !a b"' in tree


def test_masks_and_short_sequences(spark):
    items = spark.createDataFrame([(1, 1, "a"), (1, 2, "c"), (2, 1, "b"), (3, 1, "z")], "sid long, pos int, item string")
    assert {r["sid"]: r["mask"] for r in measures.item_masks(items, ["a", "b", "c"]).collect()} == {1: 5, 2: 2}
    assert {r["sid"] for r in S.drop_short(items, 2).collect()} == {1}
    with pytest.raises(ValueError):
        measures.item_masks(items, [str(k) for k in range(64)])
