"""Every pair of a set is made in many tasks, however few bytes its objects take."""

import pytest

from treepairs.adapters import SETS
from treepairs.operators import bounds
from treepairs.operators.distance import all_pairs


@pytest.mark.parametrize("most", [2_000_000, 3])
def test_case_bounds_of_every_pair(spark, monkeypatch, most):
    """With ``most`` 3 the other side is not broadcast."""
    monkeypatch.setattr(bounds, "BROADCAST_ROWS", most)
    o, t = SETS["page_groups"].load(spark, "/root/testdata/sf0.001")
    got = bounds.avg_bound(None, o, t)
    want = sorted(map(tuple, bounds.avg_bound(all_pairs(o), o, t).collect()))
    assert sorted(map(tuple, got.collect())) == want and {r[2] for r in want} <= {"1a", "1b", "2", "3"}
    assert got.rdd.getNumPartitions() >= bounds.TASKS_PER_CORE * spark.sparkContext.defaultParallelism


@pytest.mark.parametrize(("sent", "rows", "cells"), [(8_000_000, 1 << 18, 1 << 22), (8_000_000, 7, 10), (3, 7, 10)])
def test_cut_average_of_every_pair(spark, monkeypatch, sent, rows, cells):
    """Nothing is shuffled by pair where the counts can be sent; with ``sent`` 3 the cells follow."""
    from treepairs.operators import every_pair

    for name, value in (("SENT_COUNTS", sent), ("PAIR_ROWS", rows), ("CUT_CELLS", cells)):
        monkeypatch.setattr(every_pair, name, value)
    o, t = SETS["user_activity"].load(spark, "/root/testdata/sf0.001")
    for level in (0, 1, 2):
        got = every_pair.avg_reduced(o, t, level)
        want = bounds.avg_reduced(all_pairs(o), o, t, level).collect()
        found = got.collect()
        assert len(found) == len(want) == 105 and {(r.a, r.b): r.bound for r in found} == {(r.a, r.b): r.bound for r in want}
        assert ("Exchange" in got._jdf.queryExecution().toString()) == (sent == 3)


@pytest.mark.parametrize(("name", "rows", "sent", "h"), [("customer_product", 40, 2_000, None), ("customer_days", 64, 4_000_000, 1), ("customer_days", 30, 500, None)])
def test_one_set_in_passes(spark, monkeypatch, name, rows, sent, h):
    """The k best pairs of a set of many blocks, with no row shuffled for a pair of blocks."""
    from treepairs.operators import dense, every_pair, passed
    from treepairs.operators.emd_join import emd_topk
    from treepairs.operators.search import ranked

    def dealt(*_):
        raise AssertionError("rows are dealt into cells")

    monkeypatch.setattr(dense, "_dealt", dealt)
    monkeypatch.setattr(dense.Classes, "inside", lambda *_: (0, float("inf")))  # as if no two objects were equal
    monkeypatch.setattr(passed, "PARTS_PER_CORE", 1)
    monkeypatch.setattr(passed, "SENT_TERMS", sent)
    o, t = SETS[name].load(spark, "/root/testdata/sf0.001")
    want = list(map(tuple, ranked(every_pair.nearest(o, t, "emd", 7), 7).collect()))
    assert len(want) == 7 and list(map(tuple, emd_topk(o, t, 7, h=h, block_rows=rows).collect())) == want
