"""The registered queries of the pair searches and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .adapters import SETS, word_sets
from .ontology import Ontology, dag_to_tree
from .operators import avg_join, baselines, bounds, emd_join, every_pair, extensions, flow, measures, min_join, objects, relational, worded
from .operators.distance import all_pairs, sandwich
from .operators.ordered_pairs import ordered_gaps
from .registry_variants import QUERIES as VARIANTS
from .sql import LEAVES, closure_sql, counts_sql, distances_sql, key_sql, knn_sql, range_sql, topk_sql
from .streaming.windows import stream_topk_windows, windows_topk_sql

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}
K = 10


def _add(name: str, query: Query, sql: str | None = None) -> None:
    _QUERIES[name] = query
    if sql is not None:
        _SQL[name] = sql


def _search(name: str, data: str, measure: str, run: Callable, k: int = K, sql: bool | str = True) -> None:
    _add(name, lambda spark, sf: run(*SETS[data].load(spark, sf)), topk_sql(data, measure, k) if sql is True else sql or None)


# -- earth mover's distance -------------------------------------------------------------------------------------------
_search("emd_topk_parts_geo", "part_geo", "emd", lambda o, t: emd_join.emd_topk(o, t, K))
_search("emd_topk_customers_product", "customer_product", "emd", lambda o, t: emd_join.emd_topk(o, t, K))
_search("emd_topk_users_activity", "user_activity", "emd", lambda o, t: emd_join.emd_topk(o, t, K))
_search("emd_topk_customers_days", "customer_days", "emd", lambda o, t: emd_join.emd_topk(o, t, K))
_search("emd_topk_parts_market", "part_market", "emd", lambda o, t: emd_join.emd_topk(o, t, K))
_search("emd_topk_vectors", "vector_groups", "emd", lambda o, t: emd_join.emd_topk(o, t, K))


def _docs(spark: SparkSession, sf: str, k: int) -> DataFrame:
    return worded.emd_topk(word_sets(spark, sf, "doc_words"), k, lambda: emd_join.emd_topk(*SETS["doc_words"].load(spark, sf), k))


_add("emd_topk_docs_lexical", lambda s, sf: _docs(s, sf, K), topk_sql("doc_words", "emd", K))
_search("emd_topk_l1full", "user_activity", "emd", lambda o, t: emd_join.emd_topk(o, t, K, variant="l1_full"))
_search("emd_topk_l1reduced", "part_geo", "emd", lambda o, t: emd_join.emd_topk(o, t, K, variant="l1_reduced"))
_search("emd_topk_edge", "part_geo", "emd", lambda o, t: emd_join.emd_topk(o, t, K, variant="edge", h=1))
_search("emd_reduced_topk", "part_geo", "emd", lambda o, t: baselines.emd_reduced_topk(o, t, K))
_search("emd_reduced_filter", "customer_product", "emd", lambda o, t: baselines.emd_reduced_topk(o, t, K))
_search("emd_topk_progressive", "user_activity", "emd", lambda o, t: emd_join.emd_topk(o, t, K, variant="l1_reduced", engine="progressive"))
_search("emd_topk_orders_dedup", "order_geo", "emd", lambda o, t: emd_join.emd_topk(o, t, K, dedupe=True), sql=f"""
WITH leaf AS ({LEAVES["order_geo"][0]}), t AS (SELECT obj_id, list(k3 ORDER BY k3) AS terms FROM leaf GROUP BY obj_id),
d AS (SELECT x.obj_id AS a, y.obj_id AS b, CAST(0 AS DOUBLE) AS dist FROM t x JOIN t y ON x.terms = y.terms AND x.obj_id < y.obj_id)
SELECT CAST(row_number() OVER (ORDER BY dist, a, b) AS INTEGER) AS rank, a, b, dist FROM d ORDER BY dist, a, b LIMIT {K}""")


def _bipartite(spark: SparkSession, sf: str) -> DataFrame:
    left, tree = SETS["supplier_product"].load(spark, sf)
    return emd_join.emd_topk(left, tree, K, right=SETS["part_product"].objects(spark, sf))


_add("emd_bipartite_suppliers_parts", _bipartite, topk_sql("supplier_product", "emd", K, "part_product"))


def _doc_items(spark: SparkSession, sf: str) -> DataFrame:
    def general() -> DataFrame:
        docs, items = SETS["doc_words"].leaves(spark, sf), SETS["benchmark_words"].leaves(spark, sf)
        tree = Ontology.from_levels(docs.select("k1", "k2", "k3", "k4").unionByName(items.select("k1", "k2", "k3", "k4")), [F.col(f"k{i}") for i in range(1, 5)])
        return emd_join.emd_topk(SETS["doc_words"].objects(spark, sf), tree, K, right=SETS["benchmark_words"].objects(spark, sf))

    return worded.emd_topk(word_sets(spark, sf, "doc_words"), K, general, word_sets(spark, sf, "benchmark_words"))


_add("emd_bipartite_docs_benchmark", _doc_items, topk_sql("doc_words", "emd", K, "benchmark_words"))
_add("emd_range_users", lambda s, sf: extensions.range_join(*SETS["user_activity"].load(s, sf), 0.6), range_sql("user_activity", "emd", 0.6))


def _knn(measure: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        o, tree = SETS["part_geo"].load(spark, sf)
        return extensions.knn(o, tree, o.filter("obj_id % 100 = 0"), 5, measure)

    return run


_add("emd_knn_parts", _knn("emd"), knn_sql("part_geo", "emd", 5, "x.obj_id % 100 = 0"))


def _flow_small(spark: SparkSession, sf: str) -> DataFrame:
    o, tree = SETS["page_groups"].load(spark, sf)
    f = flow.emd_flow(all_pairs(o), o, tree)
    return f.groupBy("a", "b").agg(F.sum("cost").alias("total_cost"), F.sum("flow").alias("total_flow"))


_add("emd_flow_small", _flow_small, f"WITH {distances_sql('page_groups', 'emd')} SELECT a, b, CAST(round(dist * na * nb * 4) AS BIGINT) AS total_cost, CAST(na * nb AS BIGINT) AS total_flow FROM d")


def _ladder_sql() -> str:
    parts = [f"q{h} AS (WITH {distances_sql('page_groups', 'emd', upto=h)} SELECT a, b, dist FROM d)" for h in (1, 2, 3)]
    return "WITH " + ", ".join(parts) + " SELECT q1.a, q1.b, q1.dist AS h1, q2.dist AS h2, q3.dist AS h3 FROM q1 JOIN q2 ON q1.a = q2.a AND q1.b = q2.b JOIN q3 ON q1.a = q3.a AND q1.b = q3.b"


_add("emd_bounds_ladder", lambda s, sf: every_pair.emd_ladder(*SETS["part_geo"].load(s, sf), (1, 2, 3)))
_add("emd_bounds_ladder_pages", lambda s, sf: every_pair.emd_ladder(*SETS["page_groups"].load(s, sf), (1, 2, 3)), _ladder_sql())

# -- minimum distance -------------------------------------------------------------------------------------------------
_search("min_topk_customers_product", "customer_product", "min", lambda o, t: min_join.mindist_topk(o, t, K))
_search("min_topk_parts_geo", "part_geo", "min", lambda o, t: min_join.mindist_topk(o, t, K))
_search("min_topk_levels", "user_activity", "min", lambda o, t: min_join.mindist_topk(o, t, K, engine="levels"))


def _sqrt_list(spark: SparkSession, sf: str) -> DataFrame:
    o, tree = SETS["part_geo"].load(spark, sf)
    return measures.agreement(min_join.mindist_topk(o, tree, K, list_len="sqrt"), min_join.mindist_topk(o, tree, K))


_add("min_topk_sqrt_list", _sqrt_list)


def _keyword(spark: SparkSession, sf: str) -> DataFrame:
    return extensions.keyword_search(*SETS["doc_words"].load(spark, sf), "4:a/an/and/and", K)


_add("min_keyword_docs", _keyword, f"""
WITH leaf AS ({LEAVES["doc_words"][0]}), d AS (SELECT obj_id, min(CASE WHEN k4 = 'and' THEN 0 WHEN k3 = 'and' THEN 2 WHEN k2 = 'an' THEN 6 WHEN k1 = 'a' THEN 14 ELSE 30 END) AS num FROM leaf GROUP BY obj_id)
SELECT CAST(row_number() OVER (ORDER BY num, obj_id) AS INTEGER) AS rank, obj_id, CAST(num AS DOUBLE) / 8 AS dist FROM d ORDER BY num, obj_id LIMIT {K}""")
_add("min_range_pages", lambda s, sf: extensions.range_join(*SETS["page_groups"].load(s, sf), 0.5, "min"), range_sql("page_groups", "min", 0.5))
_add("min_single_link", lambda s, sf: extensions.single_link(*SETS["vector_groups"].load(s, sf), 0.0), f"""
WITH RECURSIVE leaf AS ({LEAVES["vector_groups"][0]}), e AS (SELECT DISTINCT x.obj_id AS a, y.obj_id AS b FROM leaf x JOIN leaf y ON x.k1 = y.k1 AND x.k2 = y.k2 AND x.k3 = y.k3),
r AS (SELECT a, b FROM e UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a) SELECT a AS obj_id, min(b) AS cluster FROM r GROUP BY a""")

# -- average distance -------------------------------------------------------------------------------------------------
_search("avg_topk_parts_geo_stepwise", "part_geo", "avg", lambda o, t: avg_join.avgdist_topk(o, t, K))
_search("avg_topk_parts_geo_complete", "part_geo", "avg", lambda o, t: avg_join.avgdist_topk(o, t, K, refine="complete"))
_search("avg_topk_customers_product", "customer_product", "avg", lambda o, t: avg_join.avgdist_topk(o, t, K))
_search("avg_topk_customers_days", "customer_days", "avg", lambda o, t: avg_join.avgdist_topk(o, t, K))
_search("avg_topk_progressive", "user_activity", "avg", lambda o, t: avg_join.avgdist_topk(o, t, K, engine="progressive"))
_add("avg_build_root", lambda s, sf: objects.avg_build(*SETS["customer_days"].load(s, sf)).filter("level = 0").select("obj_id", "n", "w"), f"WITH {counts_sql('customer_days')} SELECT obj_id, n, CAST(7 * n AS BIGINT) AS w FROM sz")
_add("avg_build_levels", lambda s, sf: objects.avg_build(*SETS["customer_days"].load(s, sf), mode="levels").filter("level > 0"), f"WITH {counts_sql('customer_days')} SELECT obj_id, node AS node_id, lv AS level, c AS n, CAST(c * below AS BIGINT) AS w FROM c")


def _cases(spark: SparkSession, sf: str) -> DataFrame:
    o, tree = SETS["page_groups"].load(spark, sf)
    return bounds.avg_bound(all_pairs(o), o, tree)


_add("avg_case_bounds", lambda s, sf: bounds.avg_bound(None, *SETS["customer_days"].load(s, sf)))
_add("avg_case_bounds_pages", _cases, f"""
WITH {counts_sql('page_groups')}, sp AS (SELECT obj_id, count(*) AS k, min(node) AS node FROM c WHERE lv = 1 GROUP BY obj_id),
o AS (SELECT sz.obj_id, n, 7 * n AS w, k, node FROM sz JOIN sp USING (obj_id)),
p AS (SELECT x.obj_id AS a, y.obj_id AS b, x.n AS na, y.n AS nb, x.w AS wa, y.w AS wb, CASE WHEN x.k = 1 AND y.k = 1 AND x.node = y.node THEN '1a' WHEN x.k = 1 AND y.k = 1 THEN '1b' WHEN x.k = 1 OR y.k = 1 THEN '3' ELSE '2' END AS "case", x.k AS ka
  FROM o x JOIN o y ON x.obj_id < y.obj_id)
SELECT a, b, "case", CAST(CASE "case" WHEN '1a' THEN 0 WHEN '1b' THEN nb * wa + na * wb WHEN '3' THEN CASE WHEN ka = 1 THEN wa ELSE wb END ELSE wa + wb END AS DOUBLE) / CAST(na * nb * 4 AS DOUBLE) AS bound FROM p""")


_add("avg_descend_levels", lambda s, sf: every_pair.avg_descend(*SETS["customer_days"].load(s, sf), 3))
_add("avg_descend_levels_pages", lambda s, sf: every_pair.avg_descend(*SETS["page_groups"].load(s, sf), 3),  # the deepest level: the exact distance
     f"WITH {distances_sql('page_groups', 'avg')} SELECT a, b, dist AS bound FROM d")
_add("avg_knn", _knn("avg"), knn_sql("part_geo", "avg", 5, "x.obj_id % 100 = 0"))
_add("avg_range", lambda s, sf: extensions.range_join(*SETS["customer_days"].load(s, sf), 2.0, "avg"), range_sql("customer_days", "avg", 2.0))

# -- baselines --------------------------------------------------------------------------------------------------------
_search("brute_emd", "user_activity", "emd", lambda o, t: baselines.brute_force(o, t, "emd", K))
_search("brute_emd_join", "user_activity", "emd", lambda o, t: baselines.brute_force(o, t, "emd", K, engine="join"))
_search("brute_emd_flow", "page_groups", "emd", lambda o, t: baselines.brute_force(o, t, "emd", K, engine="flow"))
_search("brute_min", "part_geo", "min", lambda o, t: baselines.brute_force(o, t, "min", K))
_search("brute_avg", "user_activity", "avg", lambda o, t: baselines.brute_force(o, t, "avg", K))

# -- trees and preparation --------------------------------------------------------------------------------------------
_TREES = {"geo": "part_geo", "product": "part_product", "calendar": "customer_days", "activity": "user_activity", "lexical": "doc_words", "web": "page_groups", "vector": "vector_groups", "market": "part_market"}
_GEO_TREE = "SELECT DISTINCT n_regionkey AS k1, n_nationkey AS k2, s_suppkey AS k3 FROM supplier JOIN nation ON s_nationkey = n_nationkey"


def _tree_sql(data: str) -> str:
    query, h = LEAVES[data]
    query = _GEO_TREE if data == "part_geo" else query
    parts = ["SELECT 'root' AS node_id, CAST(NULL AS VARCHAR) AS parent_id, 0 AS level, CAST(0 AS BIGINT) AS w, CAST(0 AS BIGINT) AS depth"]
    depth = 0
    for lv in range(1, h + 1):
        depth += 2 ** (h - lv)
        parts.append(f"SELECT DISTINCT {key_sql(lv)}, {key_sql(lv - 1) if lv > 1 else repr('root')}, {lv}, CAST({2 ** (h - lv)} AS BIGINT), CAST({depth} AS BIGINT) FROM leaf")
    return f"WITH leaf AS ({query}) " + " UNION ALL ".join(parts)


for _name, _data in _TREES.items():
    _add(f"ontology_{_name}", lambda s, sf, d=_data: SETS[d].ontology(s, sf).nodes.select("node_id", "parent_id", "level", "w", "depth"), _tree_sql(_data))

_CLOSURE = f"""
WITH RECURSIVE n AS ({_tree_sql('part_geo')}), up AS (
  SELECT node_id, node_id AS anc_id, level AS anc_level, CAST(0 AS BIGINT) AS dist FROM n UNION ALL
  SELECT up.node_id, n.parent_id, n.level - 1, up.dist + n.w FROM up JOIN n ON up.anc_id = n.node_id WHERE n.parent_id IS NOT NULL)
SELECT node_id, anc_id, anc_level, dist FROM up"""
_add("closure_geo", lambda s, sf: SETS["part_geo"].ontology(s, sf).closure(), _CLOSURE)
_add("closure_recursive_sql", lambda s, sf: closure_sql(s, SETS["part_geo"].ontology(s, sf).nodes), _CLOSURE)


def _dag(spark: SparkSession, sf: str) -> DataFrame:
    """Nations below their region and below the region after it: the shallowest, then smallest parent stays."""
    n = spark.read.parquet(f"{sf}/nation.parquet")
    up = n.select(F.concat(F.lit("n"), "n_nationkey").alias("child"), F.explode(F.array(F.col("n_regionkey"), (F.col("n_regionkey") + 1) % 5)).alias("r"))
    r = spark.read.parquet(f"{sf}/region.parquet").select(F.concat(F.lit("r"), "r_regionkey").alias("child"), F.lit("root").alias("parent"))
    root = spark.range(1).select(F.lit("root").alias("child"), F.lit(None).cast("string").alias("parent"))
    return dag_to_tree(up.select("child", F.concat(F.lit("r"), "r").alias("parent")).unionByName(r).unionByName(root))


_add("dag_to_tree", _dag, """
SELECT 'root' AS child, CAST(NULL AS VARCHAR) AS parent UNION ALL SELECT 'r' || r_regionkey, 'root' FROM region UNION ALL
SELECT 'n' || n_nationkey, 'r' || least(n_regionkey, (n_regionkey + 1) % 5) FROM nation""")
_add("cut_tree", lambda s, sf: SETS["part_geo"].ontology(s, sf).cut(1), f"WITH n AS ({_tree_sql('part_geo')}), s AS ({_GEO_TREE}) SELECT node_id AS term_id, node_id AS kept_id FROM n WHERE level <= 1 UNION ALL SELECT DISTINCT {key_sql(2)}, {key_sql(1)} FROM s UNION ALL SELECT DISTINCT {key_sql(3)}, {key_sql(1)} FROM s")


def _inverted(spark: SparkSession, sf: str) -> DataFrame:
    return objects.inverted_index(SETS["user_activity"].objects(spark, sf)).select("term_id", F.size("objects").cast("long").alias("n"), F.array_join("objects", ",").alias("objects"))


_add("inverted_index", _inverted, f"WITH leaf AS ({LEAVES['user_activity'][0]}) SELECT {key_sql(2)} AS term_id, count(*) AS n, string_agg(CAST(obj_id AS VARCHAR), ',' ORDER BY obj_id) AS objects FROM leaf GROUP BY 1")
_add("dedupe_sets", lambda s, sf: objects.dedupe_objects(SETS["order_geo"].objects(s, sf))[1], f"WITH leaf AS ({LEAVES['order_geo'][0]}), t AS (SELECT obj_id, list(k3 ORDER BY k3) AS terms FROM leaf GROUP BY obj_id) SELECT obj_id, min(obj_id) OVER (PARTITION BY terms) AS rep FROM t")
_add("mass_vectors", lambda s, sf: objects.mass(SETS["user_activity"].objects(s, sf)).select("obj_id", "term_id", (F.col("cnt") / F.col("n")).alias("mass")), f"WITH {counts_sql('user_activity')} SELECT obj_id, node AS term_id, CAST(1 AS DOUBLE) / n AS mass FROM c JOIN sz USING (obj_id) WHERE lv = 2")
_add("reduced_vectors", lambda s, sf: objects.reduce_objects(*SETS["part_geo"].load(s, sf), 1), f"WITH {counts_sql('part_geo')} SELECT obj_id, node AS term_id, c AS cnt, n FROM c JOIN sz USING (obj_id) WHERE lv = 1")
_add("spans", lambda s, sf: objects.spans(objects.avg_build(*SETS["customer_days"].load(s, sf))), f"WITH {counts_sql('customer_days')}, sp AS (SELECT obj_id, count(*) AS k, min(node) AS node FROM c WHERE lv = 1 GROUP BY obj_id) SELECT obj_id, n, CAST(7 * n AS BIGINT) AS w, k AS children, CASE WHEN k > 1 THEN 'n=' || n ELSE node END AS list_id FROM sz JOIN sp USING (obj_id)")
_add("subtree_counts_rollup", lambda s, sf: objects.avg_rollup(SETS["user_activity"].leaves(s, sf).distinct(), ["k1", "k2"]).select("obj_id", F.col("depth").cast("int").alias("depth"), F.coalesce("k1", F.lit("")).alias("k1"), F.coalesce(F.col("k2"), F.lit(-1)).cast("long").alias("k2"), "n"), f"WITH leaf AS ({LEAVES['user_activity'][0]}) SELECT obj_id, 0 AS depth, '' AS k1, CAST(-1 AS BIGINT) AS k2, count(*) AS n FROM leaf GROUP BY obj_id UNION ALL SELECT obj_id, 1, k1, -1, count(*) FROM leaf GROUP BY obj_id, k1 UNION ALL SELECT obj_id, 2, k1, CAST(k2 AS BIGINT), count(*) FROM leaf GROUP BY obj_id, k1, k2")


def _terms(height: int | None) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        tree = SETS["part_geo"].ontology(spark, sf)
        n = tree.nodes.select("node_id")
        return tree.term_distance(n.select(F.col("node_id").alias("x")).crossJoin(n.select(F.col("node_id").alias("y"))), height)

    return run


def _terms_sql(height: int | None) -> str:
    """Distances by common ancestors: the least sum of the two ways up."""
    cut = "" if height is None else f"WHERE anc_level <= {height}"
    start = "dist" if height is None else "dist - min(dist) OVER (PARTITION BY node_id)"
    return f"WITH cl AS ({_CLOSURE}), u AS (SELECT node_id, anc_id, {start} AS dist FROM cl {cut}) SELECT p.node_id AS x, q.node_id AS y, CAST(min(p.dist + q.dist) AS DOUBLE) / 4 AS dist FROM u p JOIN u q ON p.anc_id = q.anc_id GROUP BY 1, 2"


_add("term_distance", _terms(None), _terms_sql(None))
_add("term_distance_cut", _terms(1), _terms_sql(1))

# -- measures ---------------------------------------------------------------------------------------------------------
_add("eta_emd", lambda s, sf: measures.eta_emd(*SETS["user_activity"].load(s, sf), K))
_add("eta_avg", lambda s, sf: measures.eta_avg(*SETS["user_activity"].load(s, sf), K))


def _purity(spark: SparkSession, sf: str) -> DataFrame:
    lang = spark.read.parquet(f"{sf}/documents.parquet").select(F.col("doc_id").alias("obj_id"), F.col("lang").alias("category"))
    return measures.purity(_docs(spark, sf, 50), lang)


_add("purity_topk", _purity, f"""
WITH t AS ({topk_sql('doc_words', 'emd', 50)}), j AS (SELECT t.rank, x.lang = y.lang AS same FROM t JOIN documents x ON t.a = x.doc_id JOIN documents y ON t.b = y.doc_id)
SELECT cut, count(*) AS pairs, count(*) FILTER (WHERE same) AS same FROM j JOIN (VALUES (10), (50)) v(cut) ON rank <= cut GROUP BY cut""")
_add("zero_pairs", lambda s, sf: measures.zero_pairs(SETS["page_groups"].objects(s, sf)), f"WITH leaf AS ({LEAVES['page_groups'][0]}) SELECT count(DISTINCT x.obj_id * 1000000000 + y.obj_id) AS zero FROM leaf x JOIN leaf y ON x.k1 = y.k1 AND x.k2 = y.k2 AND x.k3 = y.k3 AND x.obj_id < y.obj_id")


def _tight_sql() -> str:
    e = f"e AS (WITH {distances_sql('page_groups', 'emd')} SELECT a, b, dist FROM d)"
    rows = [f"q{h} AS (WITH {distances_sql('page_groups', 'emd', upto=h)} SELECT a, b, dist FROM d)" for h in (1, 2)]
    l1 = lambda lv, f: f"(WITH {counts_sql('page_groups')}, x AS (SELECT c.*, n FROM c JOIN sz USING (obj_id) WHERE lv = {lv}), s AS (SELECT x.obj_id AS a, y.obj_id AS b, CAST(sum(least(x.c * y.n, y.c * x.n)) AS BIGINT) AS m FROM x JOIN x y ON x.node = y.node AND x.obj_id < y.obj_id GROUP BY 1, 2), p AS (SELECT x.obj_id AS a, y.obj_id AS b, x.n * y.n AS den FROM sz x JOIN sz y ON x.obj_id < y.obj_id) SELECT p.a, p.b, CAST(den - coalesce(m, 0) AS DOUBLE) / den * {f} AS dist FROM p LEFT JOIN s ON p.a = s.a AND p.b = s.b)"
    rows += [f"q3 AS {l1(1, 1.0)}", f"q4 AS {l1(3, 0.25)}"]
    union = " UNION ALL ".join(f"SELECT '{n}' AS bound, count(*) AS pairs, count(*) FILTER (WHERE q.dist > e.dist + 1e-9) AS violations, round(avg(CASE WHEN e.dist > 0 THEN q.dist / e.dist END), 6) AS mean_ratio FROM e JOIN q{i} q ON e.a = q.a AND e.b = q.b" for i, n in enumerate(("edge_1", "edge_2", "l1_reduced", "l1_full"), 1))
    return f"WITH {e}, {', '.join(rows)} {union}"


def _tight(data: str) -> Query:
    return lambda s, sf: every_pair.tightness(*SETS[data].load(s, sf)).withColumn("mean_ratio", F.round("mean_ratio", 6))


_add("bound_tightness", _tight("part_geo"))
_add("bound_tightness_pages", _tight("page_groups"), _tight_sql())


def _sandwich(spark: SparkSession, sf: str) -> DataFrame:
    o, tree = SETS["page_groups"].load(spark, sf)
    p = all_pairs(o)
    n = sandwich(p, o, tree).agg(F.count(F.lit(1)).alias("violations"))
    return p.agg(F.count(F.lit(1)).alias("pairs")).crossJoin(n)


_add("sandwich_check", lambda s, sf: every_pair.sandwich(*SETS["part_geo"].load(s, sf)))
_add("sandwich_check_pages", _sandwich, f"""
WITH m AS (WITH {distances_sql('page_groups', 'min')} SELECT a, b, dist FROM d), e AS (WITH {distances_sql('page_groups', 'emd')} SELECT a, b, dist FROM d), v AS (WITH {distances_sql('page_groups', 'avg')} SELECT a, b, dist FROM d)
SELECT count(*) AS pairs, count(*) FILTER (WHERE m.dist > e.dist OR e.dist > v.dist) AS violations FROM m JOIN e ON m.a = e.a AND m.b = e.b JOIN v ON m.a = v.a AND m.b = v.b""")
_add("list_sizes_min", lambda s, sf: min_join.list_sizes(*SETS["part_geo"].load(s, sf), K), f"""
WITH {counts_sql('part_geo')}, g AS (SELECT lv AS level, node, count(*) AS n FROM c GROUP BY ALL UNION ALL SELECT 0, 'root', count(*) FROM sz)
SELECT level, count(*) AS nodes, max(least(n, {K + 1})) AS most, CAST(sum(least(n, {K + 1})) AS BIGINT) AS kept FROM g GROUP BY level""")

# -- extensions -------------------------------------------------------------------------------------------------------
_add("multi_ontology_topk", lambda s, sf: extensions.multi_topk([SETS["customer_product"].load(s, sf), SETS["customer_days"].load(s, sf)], K), f"""
WITH p AS (WITH {distances_sql('customer_product', 'emd')} SELECT a, b, dist FROM d), t AS (WITH {distances_sql('customer_days', 'emd')} SELECT a, b, dist FROM d), d AS (SELECT p.a, p.b, p.dist + t.dist AS dist FROM p JOIN t ON p.a = t.a AND p.b = t.b)
SELECT CAST(row_number() OVER (ORDER BY dist, a, b) AS INTEGER) AS rank, a, b, dist FROM d ORDER BY dist, a, b LIMIT {K}""")


def _gaps(spark: SparkSession, sf: str) -> DataFrame:
    v = spark.read.parquet(f"{sf}/supplier.parquet").select(F.col("s_nationkey").alias("dim"), F.col("s_suppkey").alias("id"), F.col("s_acctbal").cast("double").alias("value"))
    return ordered_gaps(v, 5).select("nth", "a", "b", F.round("gap", 6).alias("gap"))


_add("ordered_gaps", _gaps, """
WITH g AS (SELECT x.s_nationkey AS dim, least(x.s_suppkey, y.s_suppkey) AS a, greatest(x.s_suppkey, y.s_suppkey) AS b, abs(CAST(x.s_acctbal AS DOUBLE) - CAST(y.s_acctbal AS DOUBLE)) AS gap FROM supplier x JOIN supplier y ON x.s_nationkey = y.s_nationkey AND x.s_suppkey < y.s_suppkey),
r AS (SELECT *, row_number() OVER (PARTITION BY dim ORDER BY gap, a, b) AS nth FROM g) SELECT CAST(nth AS INTEGER) AS nth, a, b, round(gap, 6) AS gap FROM r WHERE nth <= 5""")
_add("stream_topk_windows", stream_topk_windows, windows_topk_sql())
_add("distances_given_pairs", lambda s, sf: every_pair.distances(*SETS["part_market"].load(s, sf)).select("a", "b", "emd", "avg", "min"))
_add("distances_given_pairs_pages", lambda s, sf: every_pair.distances(*SETS["page_groups"].load(s, sf)).select("a", "b", "emd", "avg", "min"), f"""
WITH m AS (WITH {distances_sql('page_groups', 'min')} SELECT a, b, dist FROM d), e AS (WITH {distances_sql('page_groups', 'emd')} SELECT a, b, dist FROM d), v AS (WITH {distances_sql('page_groups', 'avg')} SELECT a, b, dist FROM d)
SELECT m.a, m.b, m.dist AS min, e.dist AS emd, v.dist AS avg FROM m JOIN e ON m.a = e.a AND m.b = e.b JOIN v ON m.a = v.a AND m.b = v.b""")


for _name, (_query, _text) in (relational.QUERIES | VARIANTS).items():
    _add(_name, _query, _text)


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
