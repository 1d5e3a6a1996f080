"""Searches, variants and bounds against brute force on random trees."""

import random
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from treepairs.functions.weights import by_level
from treepairs.ontology import Ontology
from treepairs.operators import avg_join, baselines, bounds, emd_join, extensions, measures, min_join, objects
from treepairs.operators.distance import DISTANCES, all_pairs, avg_distance, emd_distance, min_distance
from treepairs.operators.flow import path_distance, solve, transport
from treepairs.operators.ordered_pairs import ordered_gaps, ordered_pairs
from treepairs.operators.progressive import GapStream
from treepairs.operators.search import Metrics


def random_set(seed, n=14, terms=25, size=4):
    rnd = random.Random(seed)
    parent = {"0": None}
    for i in range(1, terms):
        parent[str(i)] = str(rnd.randrange(max(0, i - 8), i))
    objs = {i * 3 + 1: rnd.sample(sorted(parent), rnd.randint(1, size)) for i in range(n)}
    objs[500] = objs[1]
    return parent, objs


def load(spark, seed, rule=None, **k):
    parent, objs = random_set(seed, **k)
    edges = spark.createDataFrame(list(parent.items()), "child string, parent string")
    tree = Ontology.from_edges(edges, rule=rule)
    nodes = spark.createDataFrame(tree.nodes.collect(), tree.nodes.schema)
    tree = Ontology(nodes, tree.scale, tree.height, tree.least_edge, tree.least_top_edge)
    return spark.createDataFrame([(i, t) for i, ts in objs.items() for t in ts], "obj_id long, term_id string"), tree


def exact(tree, o):
    """All distances by plain Python."""
    path = {r.node_id: [(s.node_id, s.depth) for s in r.path] for r in tree.nodes.collect()}
    by = {}
    for r in o.collect():
        by.setdefault(r.obj_id, set()).add(r.term_id)
    out = {"min": {}, "avg": {}, "emd": {}}
    for a, b in combinations(sorted(by), 2):
        x, y = [path[t] for t in sorted(by[a])], [path[t] for t in sorted(by[b])]
        d = [path_distance(p, q) for p in x for q in y]
        out["min"][a, b] = min(d) / tree.scale
        out["avg"][a, b] = sum(d) / (len(d) * tree.scale)
        out["emd"][a, b] = solve(x, y)[0] / (len(d) * tree.scale)
    return out


def best(table, k):
    return sorted((d, a, b) for (a, b), d in table.items())[:k]


def same(x, y):
    return [tuple(r)[1:] for r in x] == [tuple(r)[1:] for r in y] and [r[0] for r in x] == pytest.approx([r[0] for r in y], abs=1e-12)


def got(df):
    return [(r.dist, r.a, r.b) for r in df.orderBy("rank").collect()]


@pytest.fixture(scope="module", params=[(1, None), (3, by_level(["1.5", "0.25", "0.7", "2", "0.5", "1", "0.3", "0.9", "1", "1", "1", "1"]))], ids=["halving", "any"])
def case(request, spark):
    seed, rule = request.param
    o, t = load(spark, seed, rule)
    return o.cache(), t, exact(t, o)


def test_distances(case):
    o, t, want = case
    p = all_pairs(o)
    for name, f in DISTANCES.items():
        assert {(r.a, r.b): r.dist for r in f(p, o, t).collect()} == pytest.approx(want[name], abs=1e-12)


@pytest.mark.parametrize("variant", ["edge", "l1_reduced", "l1_full", "emd_reduced", "brute"])
def test_emd_variants(case, variant):
    o, t, want = case
    for k in (1, 6):
        assert same(got(emd_join.emd_topk(o, t, k, variant=variant)), best(want["emd"], k))
    assert same(got(emd_join.emd_topk(o, t, 5, variant=variant, engine="progressive")), best(want["emd"], 5))


def test_many_blocks(case):
    o, t, want = case
    m = Metrics()
    assert same(got(emd_join.emd_topk(o, t, 7, block_rows=4, metrics=m)), best(want["emd"], 7))
    assert m.pairs("exact") <= len(want["emd"])
    assert same(got(avg_join.avgdist_topk(o, t, 7, block_rows=4)), best(want["avg"], 7))


def test_min_engines(case):
    o, t, want = case
    for k in (1, 5, 40):
        assert same(got(min_join.mindist_topk(o, t, k)), best(want["min"], k))
    assert same(got(min_join.mindist_topk(o, t, 5, engine="levels")), best(want["min"], 5))
    assert same(got(baselines.brute_force(o, t, "min", 5)), best(want["min"], 5))


def test_avg_engines(case):
    o, t, want = case
    for refine in ("stepwise", "complete"):
        assert same(got(avg_join.avgdist_topk(o, t, 6, refine=refine)), best(want["avg"], 6))
        for order in ("bfs", "dfs"):
            assert same(got(avg_join.avgdist_topk(o, t, 6, refine=refine, order=order, engine="progressive")), best(want["avg"], 6))
    assert same(got(baselines.brute_force(o, t, "avg", 4)), best(want["avg"], 4))


def test_bounds_hold(case):
    o, t, want = case
    p = all_pairs(o)
    kinds = [("emd", bounds.l1_full(p, o, t)), ("emd", bounds.l1_reduced(p, o, t)), ("avg", bounds.avg_bound(p, o, t))]
    kinds += [("emd", bounds.emd_reduced(p, o, t, h)) for h in (1, 2)] + [("avg", bounds.avg_reduced(p, o, t, 1))]
    for name, b in kinds:
        rows = b.collect()
        assert len(rows) == len(want[name]) and all(r.bound <= want[name][r.a, r.b] + 1e-9 for r in rows), name
    for r in bounds.avg_bound(p, o, t).filter("case = '1b'").collect():
        assert r.bound == pytest.approx(want["avg"][r.a, r.b])
    last = dict.fromkeys(want["avg"], 0.0)
    for level in range(t.height + 1):
        now = {(r.a, r.b): r.bound for r in bounds.avg_descend(p, o, t, level).collect()}
        assert all(last[k] <= now[k] + 1e-9 and now[k] <= want["avg"][k] + 1e-9 for k in now)
        last = now
    assert last == pytest.approx(want["avg"])
    m = {r.obj_id: r.m for r in bounds.pivot(o, t).collect()}
    assert all(abs(m[a] - m[b]) <= d + 1e-9 for (a, b), d in want["emd"].items())
    near = {(r.a, r.b) for r in bounds.pivot_band(o, t, 0.5).collect()}
    assert near == {(a, b) for a, b in want["emd"] if abs(m[a] - m[b]) <= 0.5}


def test_residual_depth(case):
    o, t, want = case
    r = {x.obj_id: x.residual for x in bounds.residual_depth(o, t, 1).collect()}
    deep = {}
    for x in objects.subtree_counts(o, t).filter("level > 1").collect():
        deep.setdefault(x.obj_id, set()).add(x.node_id)
    apart = [(a, b) for a, b in want["emd"] if not deep.get(a, set()) & deep.get(b, set())]
    assert apart and all(want["emd"][p] + 1e-9 >= r[p[0]] + r[p[1]] for p in apart)


def test_build_modes_and_spans(case):
    o, t, _ = case
    rows = lambda df: sorted(map(tuple, df.select("obj_id", "node_id", "level", "n", "w").collect()))
    assert rows(objects.avg_build(o, t)) == rows(objects.avg_build(o, t, "levels"))
    assert objects.spans(objects.avg_build(o, t)).count() == o.select("obj_id").distinct().count()
    heads = {(r.la, r.lb): r.head for r in avg_join.list_pairs(o, t).collect()}
    home = {r.obj_id: r.list_id for r in avg_join.ordered_lists(o, t).collect()}
    for r in bounds.avg_bound(all_pairs(o), o, t).collect():
        assert heads[tuple(sorted((home[r.a], home[r.b])))] <= r.bound + 1e-9


def test_range_knn_and_two_sets(case):
    o, t, want = case
    for measure in ("emd", "avg", "min"):
        radius = sorted(want[measure].values())[len(want[measure]) // 3]
        rows = {(r.a, r.b): r.dist for r in extensions.range_join(o, t, radius, measure).collect()}
        assert rows == pytest.approx({k: d for k, d in want[measure].items() if d <= radius})
        full = want[measure] | {(b, a): d for (a, b), d in want[measure].items()}
        q = o.filter("obj_id < 8")
        near = extensions.knn(o, t, q, 3, measure).collect()
        for x in {r.query for r in near}:
            mine = sorted((d, b) for (a, b), d in full.items() if a == x)[:3]
            assert same([(r.dist, r.b) for r in sorted(near, key=lambda r: r["rank"]) if r["query"] == x], mine)
    left, right = o.filter("obj_id % 2 = 0"), o.filter("obj_id % 2 = 1")
    ls, rs = ({r[0] for r in s.select("obj_id").distinct().collect()} for s in (left, right))
    two = sorted((want["emd"][min(a, b), max(a, b)], a, b) for a in ls for b in rs)[:5]
    for engine in ("auto", "progressive"):
        assert same(got(emd_join.emd_topk(left, t, 5, right=right, engine=engine)), two)
    low = sorted((want["min"][min(a, b), max(a, b)], a, b) for a in ls for b in rs)[:5]
    assert same(got(min_join.mindist_topk(left, t, 5, right=right)), low)


def test_edges_of_the_input(spark, case):
    o, t, want = case
    none = o.limit(0)
    for f in (lambda x, k: emd_join.emd_topk(x, t, k), lambda x, k: min_join.mindist_topk(x, t, k), lambda x, k: avg_join.avgdist_topk(x, t, k)):
        assert f(none, 3).count() == 0 and f(o, 0).count() == 0 and f(o.filter("obj_id = 1"), 3).count() == 0
        assert f(o, 10_000).count() == len(want["emd"])
    odd = o.unionByName(spark.createDataFrame([(9_999, "no such term")], o.schema))
    assert same(got(emd_join.emd_topk(odd, t, 4)), best(want["emd"], 4))
    assert objects.unknown_terms(odd, t).count() == 1


def test_equal_descriptions(spark, case):
    o, t, want = case
    more = o.unionByName(o.filter("obj_id = 4").withColumn("obj_id", F.lit(777).cast("long")))
    plain = got(emd_join.emd_topk(more, t, 9))
    assert same(got(emd_join.emd_topk(more, t, 9, dedupe=True)), plain)
    kept, rep = objects.dedupe_objects(more)
    reps = {r.obj_id: r.rep for r in rep.collect()}
    assert reps[777] == 4 and reps[500] == 1 and kept.select("obj_id").distinct().count() == len(set(reps.values()))


def test_several_trees(spark):
    (o1, t1), (o2, t2) = load(spark, 5), load(spark, 6)
    e1, e2 = exact(t1, o1)["emd"], exact(t2, o2)["emd"]
    for agg, f in (("sum", lambda x, y: x + y), ("max", max), ("wavg", lambda x, y: (2 * x + y) / 3)):
        want = sorted((f(e1[p], e2[p]), *p) for p in e1)[:4]
        res = got(extensions.multi_topk([(o1, t1), (o2, t2)], 4, agg, weights=[2.0, 1.0], depth=8))
        assert same(res, want)


def test_clusters(spark, case):
    o, t, want = case
    cut = sorted(want["min"].values())[5]
    parent = {r[0]: r[0] for r in o.select("obj_id").distinct().collect()}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for (a, b), d in want["min"].items():
        if d <= cut:
            x, y = sorted((root(a), root(b)))
            parent[y] = x
    assert {r.obj_id: r.cluster for r in extensions.single_link(o, t, cut).collect()} == {x: root(x) for x in parent}


def test_gaps(spark):
    values = [(0.0, 5), (2.0, 1), (2.0, 4), (7.0, 2), (0.0, 3)]
    out = list(GapStream(values))
    assert len(out) == 10 and [g for g, _, _ in out] == sorted(abs(x - y) for (x, _), (y, _) in combinations(values, 2))
    assert len({(min(a, b), max(a, b)) for _, a, b in out}) == 10
    assert sorted(g for g, _, _ in GapStream(values, hashed=True)) == [g for g, _, _ in out]
    df = spark.createDataFrame([(d, i, v + d) for d in (0, 1) for v, i in values], "dim int, id long, value double")
    want = sorted((abs(x - y), min(i, j), max(i, j)) for (x, i), (y, j) in combinations(values, 2))[:6]
    for init in ("sort", "hash"):
        rows = ordered_pairs(df, 6, init).filter("dim = 1").orderBy("nth").collect()
        assert [(r.gap, r.a, r.b) for r in rows] == want
    assert ordered_gaps(df, 4).count() == 8


def test_gaps_with_ties(spark):
    """Many equal values and equal gaps: the first pairs are those of the smallest ids."""
    values = [(v, i) for i, v in enumerate([5.0, 1.0, 5.0, 3.0] * 9)]
    df = spark.createDataFrame([(0, i, v) for v, i in values], "dim int, id long, value double")
    for limit in (3, 400):
        want = sorted((abs(x - y), min(i, j), max(i, j)) for (x, i), (y, j) in combinations(values, 2))[:limit]
        assert [(r.gap, r.a, r.b) for r in ordered_gaps(df, limit).orderBy("nth").collect()] == want


def test_halved_threshold_is_exact(spark):
    """The published threshold may stop early; it must still run and give k pairs, the halved one must be exact."""
    for seed in range(3):
        o, t = load(spark, 40 + seed, n=9, terms=18, size=3)
        assert same(got(emd_join.emd_topk(o, t, 3, engine="progressive", variant="l1_reduced")), best(exact(t, o)["emd"], 3))
        assert emd_join.progressive(o, t, 3, halved=False).filter("rank > 0").count() == 3


def test_counts_and_shares(case):
    o, t, want = case
    r = measures.eta_emd(o, t, 3).first()
    assert r.pairs == len(want["emd"]) and 0 < r.eta <= 1 and r.full_l1 <= r.bounds <= r.new
    s, c = measures.eta_avg(o, t, 3).first(), measures.eta_avg(o, t, 3, "complete").first()
    assert s.complete <= c.complete and s.examined <= s.pairs
    assert measures.zero_pairs(o).first()[0] == sum(d == 0 for d in want["min"].values())
    x = measures.agreement(min_join.mindist_topk(o, t, 4), baselines.brute_force(o, t, "min", 4)).first()
    assert x.precision == 1.0 and x.kth_error == 0.0


def test_transport():
    assert transport([[0, 5], [5, 0]], [2, 2], [3, 1])[0] == 5
    cost, flows = transport([[4, 1], [2, 3]], [1, 1], [1, 1])
    assert cost == 3 and sorted(flows) == [(0, 1, 1), (1, 0, 1)]


def test_measures_agree_with_each_other(case):
    o, t, _ = case
    p = all_pairs(o)
    assert min_distance(p, o, t).count() == emd_distance(p, o, t).count() == avg_distance(p, o, t).count() == p.count()


def test_plans(spark):
    from treepairs.adapters import SETS

    o, t = SETS["part_geo"].load(spark, "/root/testdata/sf0.001")
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    p = plan(min_join.mindist_topk(o, t, 10))
    assert "WindowGroupLimit" in p and "TakeOrderedAndProject" in p and "BroadcastHashJoin" in p and "Python" not in p
    assert "CartesianProduct" not in plan(emd_join.emd_topk(o, t, 10)) and "BroadcastNestedLoop" not in plan(emd_join.emd_topk(o, t, 10))
    assert "ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint>" in plan(o)


@pytest.mark.parametrize("block_rows", [1024, 5])
def test_every_pair(case, block_rows):
    """The kernel for all pairs against the joins on given pairs."""
    from pyspark.sql import functions as F

    from treepairs.operators import every_pair

    o, t, want = case
    p = all_pairs(o)
    n = len(want["emd"])
    rows = {(r.a, r.b): r for r in every_pair.distances(o, t, block_rows).collect()}
    for m in ("emd", "avg", "min"):
        assert {k: r[m] for k, r in rows.items()} == pytest.approx(want[m])
    ladder = every_pair.emd_ladder(o, t, (1, 2), block_rows).collect()
    for h in (1, 2):
        assert {(r.a, r.b): r[f"h{h}"] for r in ladder} == {(r.a, r.b): r.bound for r in bounds.emd_reduced(p, o, t, h).collect()}
    for level in range(t.height + 1):
        assert {(r.a, r.b): r.bound for r in every_pair.avg_descend(o, t, level, block_rows).collect()} == {(r.a, r.b): r.bound for r in bounds.avg_descend(p, o, t, level).collect()}
    exact = emd_distance(p, o, t)
    tight = {r.bound: r for r in every_pair.tightness(o, t, block_rows).collect()}
    for name, b in {"edge_1": bounds.emd_reduced(p, o, t, 1), "edge_2": bounds.emd_reduced(p, o, t, 2), "l1_reduced": bounds.l1_reduced(p, o, t), "l1_full": bounds.l1_full(p, o, t)}.items():
        r = measures.tightness(b, exact).select(F.col("pairs"), "violations", "mean_ratio").first()
        assert (tight[name].pairs, tight[name].violations) == (r.pairs, r.violations) == (n, 0) and tight[name].mean_ratio == pytest.approx(r.mean_ratio)
    assert tuple(every_pair.sandwich(o, t, block_rows).first()) == (n, 0)
    assert sorted(map(tuple, bounds.avg_bound(None, o, t).collect())) == sorted(map(tuple, bounds.avg_bound(p, o, t).collect()))


@pytest.mark.parametrize("name", ["emd_bounds_ladder", "avg_case_bounds", "avg_descend_levels", "bound_tightness", "sandwich_check", "distances_given_pairs"])
def test_registered_queries_take_every_pair(spark, name):
    import __spark_entry__ as entry
    from treepairs.adapters import SETS

    sf = "/root/testdata/sf0.001"
    data = {"avg_case_bounds": "customer_days", "avg_descend_levels": "customer_days", "distances_given_pairs": "part_market"}.get(name, "part_geo")
    n = SETS[data].objects(spark, sf).select("obj_id").distinct().count()
    got = entry.queries()[name](spark, sf)
    counts = {r.pairs for r in got.select("pairs").collect()} if "pairs" in got.columns else {got.count()}
    assert counts == {n * (n - 1) // 2}
    if "pairs" not in got.columns:
        from treepairs.operators import every_pair

        o, t = SETS["page_groups"].load(spark, sf)
        every = {"emd_bounds_ladder": lambda: every_pair.emd_ladder(o, t, (1, 2, 3)), "avg_case_bounds": lambda: bounds.avg_bound(None, o, t), "avg_descend_levels": lambda: every_pair.avg_descend(o, t, 3), "distances_given_pairs": lambda: every_pair.distances(o, t)}
        held = {(r.a, r.b): r.asDict() for r in entry.queries()[f"{name}_pages"](spark, sf).collect()}
        same_rows = {(r.a, r.b): {c: r[c] for c in next(iter(held.values()))} for r in every[name]().collect()}
        assert held and held == same_rows


def test_sequential_searches_beyond_their_limit(case, monkeypatch):
    from treepairs.operators import progressive

    o, t, want = case
    monkeypatch.setattr(progressive, "MOST_OBJECTS", 5)
    assert same(got(emd_join.emd_topk(o, t, 4, variant="l1_reduced", engine="progressive")), best(want["emd"], 4))
    assert same(got(avg_join.avgdist_topk(o, t, 4, engine="progressive")), best(want["avg"], 4))
    e, a = measures.eta_emd(o, t, 3).first(), measures.eta_avg(o, t, 3).first()
    assert e.pairs == a.pairs == len(want["emd"]) and 0 < e.eta <= 1 and 0 < a.eta <= 1
    assert (e.kth, a.kth) == pytest.approx((sorted(want["emd"].values())[2], sorted(want["avg"].values())[2]))
    assert e.bounds == a.examined == e.pairs and e.calls is None and a.pops is None
