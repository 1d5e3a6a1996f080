"""Cases that were wrong once: sides of the sequential searches, ignored arguments, neighbours by lists, scales."""

import pytest
from pyspark.sql import functions as F

from treepairs.adapters import SETS
from treepairs.functions.weights import by_level
from treepairs.operators import avg_join, emd_join, extensions, measures
from treepairs.operators.distance import avg_distance, emd_distance, min_distance

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def sides(spark):
    o, tree = SETS["page_groups"].load(spark, SF)
    o = o.cache()
    low = o.agg(F.percentile_approx("obj_id", 0.5)).first()[0]
    return o.filter(F.col("obj_id") <= low), o.filter(F.col("obj_id") > low), tree


def brute(left, right, tree, measure, k):
    pairs = left.select(F.col("obj_id").alias("a")).distinct().crossJoin(right.select(F.col("obj_id").alias("b")).distinct())
    return [(r.a, r.b, r.dist) for r in measure(pairs, left, tree, right).orderBy("dist", "a", "b").limit(k).collect()]


def rows(df):
    return [(r.a, r.b, r.dist) for r in df.orderBy("rank").collect()]


def test_sequential_searches_keep_to_the_sides(sides):
    left, right, tree = sides
    want = brute(left, right, tree, emd_distance, 6)
    for variant in ("l1_reduced", "emd_reduced", "brute"):
        assert rows(emd_join.emd_topk(left, tree, 6, right=right, variant=variant, engine="progressive")) == want, variant
    want = brute(left, right, tree, avg_distance, 6)
    for order in ("bfs", "dfs"):
        assert rows(avg_join.avgdist_topk(left, tree, 6, right=right, engine="progressive", order=order)) == want, order


def test_an_order_that_would_be_ignored_is_an_error(sides):
    left, _, tree = sides
    with pytest.raises(ValueError):
        avg_join.avgdist_topk(left, tree, 3, order="dfs")


def test_min_neighbours_by_node_lists(sides):
    left, right, tree = sides
    pairs = left.select(F.col("obj_id").alias("a")).distinct().crossJoin(right.select(F.col("obj_id").alias("b")).distinct())
    want = {}
    for r in min_distance(pairs, left, tree, right).orderBy("a", "dist", "b").collect():
        want.setdefault(r.a, []).append((r.b, r.dist))
    got = {}
    for r in extensions.knn(right, tree, left, 3, "min").orderBy("query", "rank").collect():
        got.setdefault(r["query"], []).append((r.b, r.dist))
    assert got == {a: x[:3] for a, x in want.items()}


def test_zero_pairs_by_classes(spark):
    terms = {1: "ab", 2: "ab", 3: "b", 4: "c", 5: "ab", 6: "c"}
    o = spark.createDataFrame([(i, t) for i, ts in terms.items() for t in ts], "obj_id long, term_id string")
    want = sum(bool(set(terms[i]) & set(terms[j])) for i in terms for j in terms if i < j)
    assert measures.zero_pairs(o).first()[0] == want


def test_level_weights_have_the_least_scale():
    assert by_level(["1.5", "0.25"])(2) == ({1: 6, 2: 1}, 4)


def test_cells_of_every_pair_in_many_blocks(spark):
    """Blocks of four objects: matrix, term pairs, cut average and nearest pairs equal the joins on given pairs."""
    from treepairs.operators import every_pair
    from treepairs.operators.bounds import avg_reduced
    from treepairs.operators.classes import Classes, expanded
    from treepairs.operators.dense import packed
    from treepairs.operators.distance import DISTANCES, all_pairs

    from test_searches import best, load, random_set

    o, t = load(spark, 3)
    p = all_pairs(o).cache()
    dist = lambda df, name="dist": {(r["a"], r["b"]): r[name] for r in df.collect()}
    for measure in ("emd", "avg", "min"):
        want = dist(DISTANCES[measure](p, o, t))
        got = dist(every_pair.matrix(o, t, measure, block_rows=4))
        assert {k: d for k, d in got.items() if k[0] < k[1]} == want and len(got) == len(want) + 15
        if measure != "emd":
            assert dist(every_pair.naive(o, t, measure, block_rows=4)) == want
    assert dist(every_pair.avg_reduced(o, t, 1, block_rows=4), "bound") == dist(avg_reduced(p, o, t, 1), "bound")
    want = dist(DISTANCES["avg"](p, o, t))
    classes = Classes.of(packed(o, t, "avg"), lambda df: df.cache())
    assert classes.table.count() == len({tuple(sorted(terms)) for terms in random_set(3)[1].values()}) == 13
    found = expanded(every_pair.nearest(classes.kept(o), t, "avg", 7, block_rows=4), classes, 7)
    assert [(r.dist, r.a, r.b) for r in found.orderBy("dist", "a", "b").limit(7).collect()] == best(want, 7)


@pytest.mark.parametrize("measure", ["emd", "avg"])
def test_searches_make_a_set_once(spark, measure):
    """Sets of many blocks are read once, kept as term numbers, and give the answers of the joins on given pairs."""
    from treepairs.operators import dense
    from treepairs.operators.distance import DISTANCES, all_pairs
    from treepairs.operators.search import answers, checkpoint

    from test_searches import best, load

    o, t = load(spark, 3)
    want = {(r.a, r.b): r.dist for r in DISTANCES[measure](all_pairs(o), o, t).collect()}
    rows, seen = o.collect(), spark.sparkContext.accumulator(0)

    def read(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    once = spark.createDataFrame(rows, o.schema).coalesce(1).mapInArrow(read, "obj_id long, term_id string")
    found = answers(dense.search(once, t, measure, 7, block_rows=4, checkpoint=checkpoint))
    assert [(r.dist, r.a, r.b) for r in found.orderBy("dist", "a", "b").limit(7).collect()] == best(want, 7)
    assert seen.value == len(rows)
    found = answers(dense.search(o, t, measure, None, radius=1.0, block_rows=4, checkpoint=checkpoint))
    assert {(r.a, r.b): r.dist for r in found.collect()} == {p: d for p, d in want.items() if d <= 1.0}


def test_numbered_nodes_equal_packed_ones(spark):
    """Blocks made of term numbers hold the same nodes, counts and sums as those of packed rows, for terms at inner nodes too."""
    from treepairs.ontology import Ontology
    from treepairs.operators.coded import Coded
    from treepairs.operators.dense import Block, packed

    t = Ontology.from_rows(spark, {"r": None, "a": "r", "b": "r", "a1": "a", "a2": "a", "a11": "a1", "b1": "b", "b2": "b"}, {"a": 5, "b": 3, "a1": 2, "a2": 4, "a11": 1, "b1": 7, "b2": 2}, 10)
    terms = {1: ["r"], 2: ["a"], 3: ["a", "a1", "a11"], 4: ["a11", "b2"], 5: ["b", "b1", "b2", "a2"], 6: ["r", "a", "b"]}
    o = spark.createDataFrame([(i, v) for i, vs in terms.items() for v in vs], "obj_id long, term_id string")
    coded = Coded.of(t, spark)
    names = {r.code: r.term_id for r in coded.codes.collect()}
    for measure in ("emd", "avg"):
        codes = {}
        y = Block(packed(o, t, measure).orderBy("obj_id").toArrow(), codes)
        back = {c: v for v, c in codes.items()}
        x_rows = coded.rows(coded.described(o), measure).orderBy("obj_id").toArrow()
        x = Block(x_rows, coded.numbers.value)
        for f in ("id", "n", "s", "single", "at"):
            assert getattr(x, f).tolist() == getattr(y, f).tolist(), f
        nodes = lambda b, name: {(int(b.row[i]), name[int(b.node[i])], int(b.level[i]), int(b.w[i]), int(b.c[i]), int(b.d[i])) for i in range(len(b.node))}
        assert nodes(x, names) == nodes(y, back)
        assert x_rows.column("self").to_pylist() == packed(o, t, measure).orderBy("obj_id").toArrow().column("self").to_pylist()


@pytest.mark.parametrize("measure", ["emd", "avg"])
def test_nearest_of_each_sent_object(spark, measure, monkeypatch):
    """Limits from nearly exact distances: the k best of each sent object, with fewer exact distances than pass by pass."""
    import numpy as np
    import pyarrow as pa

    from treepairs.operators import streamed
    from treepairs.operators.coded import Coded
    from treepairs.operators.dense import Spec
    from treepairs.operators.distance import DISTANCES, all_pairs

    from test_searches import load

    o, t = load(spark, 3)
    coded = Coded.of(t, spark)
    rows = coded.rows(coded.described(o), measure).select("obj_id", "terms").orderBy("obj_id").toArrow().combine_chunks()
    want = {}
    for r in DISTANCES[measure](all_pairs(o), o, t).collect():
        for x, y in ((r.a, r.b), (r.b, r.a)):
            want.setdefault(x, []).append((r.dist, y))
    spec = Spec(measure, 4, None, t.scale, t.height, 1, True, per_left=True)
    results = {}
    for held in (5, 1000):
        monkeypatch.setattr(streamed, "STEP_ROWS", 3)
        monkeypatch.setattr(streamed, "HELD_ROWS", held)
        for run in (streamed._passed, streamed._nearest):
            found = pa.Table.from_batches(run(spec, True, lambda: rows, coded.numbers)(iter(rows.to_batches()))).to_pylist()
            got = {}
            for r in found:
                if r["a"] is not None and r["a"] != r["b"]:
                    got.setdefault(r["a"], []).append((r["dist"], r["b"]))
            assert {a: sorted(x)[:3] for a, x in got.items()} == {a: sorted(x)[:3] for a, x in want.items()}
            results[held, run.__name__] = sum(r["exact"] for r in found)
    assert results[1000, "_nearest"] < results[1000, "_passed"]
    assert np.isfinite(list(results.values())).all()
