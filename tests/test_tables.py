import pytest

from negseq import workloads


@pytest.mark.parametrize("name", ["absence_table", "derivation_path", "exec_example", "inclusion_table", "merge_redundant", "monotonicity_cases", "occurrence_table", "rematch_case", "same_sids", "search_tree", "synthetic_gap_sweep"])
def test_reads_a_given_table(spark, monkeypatch, name):
    read, load = [], workloads.S.load
    monkeypatch.setattr(workloads.S, "load", lambda *a: read.append(a[2]) or load(*a))
    rows = workloads.QUERIES[name](spark, "/root/testdata/sf0.001").count()
    assert read and rows


def test_dealt_data_sets_on_bits(spark, monkeypatch):
    """Data sets beyond a task give the counts of small ones."""
    rows = [(u, k, "abcd"[(u * 7 + k * k) % 4]) for u in range(30) for k in range(1, 25)]
    items = spark.createDataFrame(rows, "sid long, pos int, item string")
    cells = [(long, seed, 20, gap, 0, 3) for long in (20, 30) for seed in (1, 3) for gap in (4, 0)]
    small = sorted(map(tuple, workloads.dealt_counts(items, cells).collect()))
    monkeypatch.setattr(workloads, "TASK_ROWS", 0)
    assert small == sorted(map(tuple, workloads.dealt_counts(items, cells).collect())) and len(small) == 8 and small[0][-1] > 4
