"""The worked example: every printed distance, the reductions, and the counter-examples."""

import pytest

from treepairs.functions.columns import list_length
from treepairs.functions.weights import by_level, exponential, uniform
from treepairs.ontology import Ontology, dag_to_tree
from treepairs.operators import avg_join, bounds, emd_join, min_join, objects
from treepairs.operators.distance import DISTANCES, all_pairs, distance_matrix, emd_distance, naive, sandwich
from treepairs.operators.flow import emd_flow

PARENT = {"t0": None, "t1": "t0", "t2": "t0", "t3": "t0", "t4": "t1", "t5": "t1", "t6": "t2", "t7": "t2", "t8": "t2", "t9": "t3"}
OBJECTS = {1: ["t1", "t7"], 2: ["t0", "t1", "t4", "t5"], 3: ["t2", "t3", "t9"], 4: ["t6", "t8"]}
MIN = {(1, 1): 0, (1, 2): 0, (1, 3): 0.5, (1, 4): 1, (2, 2): 0, (2, 3): 1, (2, 4): 1.5, (3, 3): 0, (3, 4): 0.5, (4, 4): 0}
AVG = {(1, 1): 1.25, (1, 2): 1.5, (1, 3): 25 / 12, (1, 4): 1.75, (2, 2): 0.75, (2, 3): 13 / 6, (2, 4): 2.5, (3, 3): 10 / 9, (3, 4): 2, (4, 4): 0.5}
EMD = {(1, 1): 0, (1, 2): 1.25, (1, 3): 1.75, (1, 4): 1.75, (2, 2): 0, (2, 3): 13 / 6, (2, 4): 2.5, (3, 3): 0, (3, 4): 2, (4, 4): 0}
REDUCED = {(1, 2): 0.5, (1, 3): 2 / 3, (1, 4): 0.5, (2, 3): 1, (2, 4): 1, (3, 4): 2 / 3}
FULL = {(1, 2): 0.75, (1, 3): 1, (1, 4): 1, (2, 3): 1, (2, 4): 1, (3, 4): 1}


def rows(spark, objs):
    return spark.createDataFrame([(i, t) for i, ts in objs.items() for t in ts], "obj_id long, term_id string")


@pytest.fixture(scope="module")
def tree(spark):
    return Ontology.from_rows(spark, PARENT)


@pytest.fixture(scope="module")
def objs(spark):
    return rows(spark, OBJECTS)


def as_dict(df, value="dist"):
    return {(r.a, r.b): r[value] for r in df.collect()}


@pytest.mark.parametrize(("measure", "want"), [("min", MIN), ("avg", AVG), ("emd", EMD)])
def test_tables(tree, objs, measure, want):
    got = as_dict(distance_matrix(objs, tree, measure))
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-12 for k in want)
    if measure != "emd":
        assert as_dict(naive(all_pairs(objs, True), objs, tree, measure)) == got


def test_flow_gives_the_same_distance(spark, tree, objs):
    p = all_pairs(objs)
    assert as_dict(emd_distance(p, objs, tree, solver="flow")) == as_dict(emd_distance(p, objs, tree))
    f = emd_flow(p, objs, tree).collect()
    total = {}
    for r in f:
        total[r.a, r.b] = total.get((r.a, r.b), 0) + r.cost
    n = {i: len(t) for i, t in OBJECTS.items()}
    assert all(abs(total[a, b] / (tree.scale * n[a] * n[b]) - EMD[a, b]) < 1e-12 for a, b in total) and len(total) == 6


def test_terms(spark, tree):
    d = {(r.x, r.y): r.dist for r in tree.term_distance(spark.createDataFrame([("t4", "t6"), ("t4", "t1"), ("t4", "t5"), ("t0", "t0")], "x string, y string")).collect()}
    assert d == {("t4", "t6"): 3, ("t4", "t1"): 0.5, ("t4", "t5"): 1, ("t0", "t0"): 0}
    assert tree.term_distance(spark.createDataFrame([("t4", "t6")], "x string, y string"), 1).first().dist == 2
    assert set(tree.check_metric().values()) == {0} and set(tree.validate().values()) == {0}
    assert tree.closure().count() == 10 + 9 + 6


def test_reduction(tree, objs):
    got = {(r.obj_id, r.term_id): r.cnt / r.n for r in objects.reduce_objects(objs, tree, 1).collect()}
    assert got == {(1, "t1"): 0.5, (1, "t2"): 0.5, (2, "t0"): 0.25, (2, "t1"): 0.75, (3, "t2"): 1 / 3, (3, "t3"): 2 / 3, (4, "t2"): 1.0}


def test_half_l1(tree, objs):
    p = all_pairs(objs)
    for got, want in ((bounds.l1_reduced(p, objs, tree), REDUCED), (bounds.l1_full(p, objs, tree, "published"), FULL)):
        d = as_dict(got, "bound")
        assert all(abs(d[k] - want[k]) < 1e-12 for k in want)


def test_minimum_is_no_metric():
    assert MIN[1, 4] + MIN[1, 2] < MIN[2, 4]


def test_order_of_the_measures(tree, objs):
    assert sandwich(all_pairs(objs), objs, tree).count() == 0


def test_unscaled_full_l1_is_no_bound(spark, tree):
    o = rows(spark, {1: ["t1"], 2: ["t4"]})
    p = all_pairs(o)
    assert as_dict(emd_distance(p, o, tree)) == {(1, 2): 0.5}
    assert as_dict(bounds.l1_full(p, o, tree, "published"), "bound") == {(1, 2): 1.0}
    assert as_dict(bounds.l1_full(p, o, tree), "bound") == {(1, 2): 0.5}
    assert as_dict(bounds.l1_reduced(p, o, tree), "bound") == {(1, 2): 0.0}


def test_short_lists_lose_a_pair(spark):
    star = Ontology.from_rows(spark, {"r": None, "a": "r", "b": "r", "c": "r"}, {"a": 10, "b": 11, "c": 12}, 10)
    o = rows(spark, {9: ["r"], 1: ["a"], 2: ["b"], 3: ["c"]})
    dists = lambda how: [r.dist for r in min_join.mindist_topk(o, star, 3, list_len=how).orderBy("rank").collect()]
    assert dists("safe") == [1.0, 1.1, 1.2] and dists("sqrt") == [1.0, 1.1, 2.1]
    assert list_length(3, "sqrt") == 3 and list_length(3) == 4


def test_ties_have_one_order(spark, tree):
    o = rows(spark, {i: ["t4", "t9"] for i in (4, 2, 3, 1)})
    want = [(1, 2), (1, 3), (1, 4)]
    for df in (emd_join.emd_topk(o, tree, 3), emd_join.emd_topk(o, tree, 3, dedupe=True), min_join.mindist_topk(o, tree, 3), avg_join.avgdist_topk(o, tree, 3), emd_join.emd_topk(o, tree, 3, engine="progressive"), avg_join.avgdist_topk(o, tree, 3, engine="progressive")):
        assert [(r.a, r.b) for r in df.orderBy("rank").collect()] == want


def test_objects_at_the_root(spark, tree):
    o = rows(spark, {1: ["t0"], 2: ["t0"], 3: ["t4"]})
    for name in DISTANCES:
        assert as_dict(DISTANCES[name](all_pairs(o), o, tree))[1, 2] == 0
    r = {(x.a, x.b): (x["case"], x.bound) for x in bounds.avg_bound(all_pairs(o), o, tree).collect()}
    assert r[1, 2] == ("1a", 0.0) and r[1, 3] == ("1b", 1.5)
    for engine in ("auto", "progressive"):
        assert [(x.a, x.b, x.dist) for x in avg_join.avgdist_topk(o, tree, 3, engine=engine).orderBy("rank").collect()] == [(1, 2, 0.0), (1, 3, 1.5), (2, 3, 1.5)]
        assert [(x.a, x.b, x.dist) for x in emd_join.emd_topk(o, tree, 3, engine=engine).orderBy("rank").collect()] == [(1, 2, 0.0), (1, 3, 1.5), (2, 3, 1.5)]


def test_weights():
    assert exponential()(3) == ({1: 4, 2: 2, 3: 1}, 4)
    assert uniform()(2) == ({1: 1, 2: 1}, 1)
    w, scale = by_level(["1.5", "0.25"])(2)
    assert w[1] / scale == 1.5 and w[2] / scale == 0.25


def test_graph_to_tree(spark):
    e = spark.createDataFrame([("r", None), ("a", "r"), ("b", "r"), ("c", "a"), ("c", "b"), ("d", "c")], "child string, parent string")
    assert {(x.child, x.parent) for x in dag_to_tree(e).collect()} == {("r", None), ("a", "r"), ("b", "r"), ("c", "a"), ("d", "c")}
    unfolded = dag_to_tree(e, "unfold")
    assert unfolded.count() == 7 and Ontology.from_edges(unfolded).validate(unfolded)["unreached"] == 0


def test_faults_are_found(spark):
    e = spark.createDataFrame([("r", None), ("a", "r"), ("x", "y"), ("y", "x"), ("a", "r")], "child string, parent string")
    t = Ontology.from_edges(e)
    v = t.validate(e)
    assert v["unreached"] == 2 and v["repeated_nodes"] == 1


def test_trees_deeper_than_allowed_are_an_error(spark):
    from treepairs.ontology import Ontology, dag_to_tree

    chain = spark.createDataFrame([("0", None), *((str(i), str(i - 1)) for i in range(1, 5))], "child string, parent string")
    assert Ontology.from_edges(chain, max_height=4).size() == 5 and dag_to_tree(chain, max_height=4).count() == 5
    for make in (lambda: Ontology.from_edges(chain, max_height=3), lambda: dag_to_tree(chain, max_height=3), lambda: dag_to_tree(chain, "unfold", max_height=3)):
        with pytest.raises(ValueError, match="deeper"):
            make()
