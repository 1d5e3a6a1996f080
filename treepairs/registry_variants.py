"""Registered queries of the variants, checks and measures beside the main searches, with their SQL."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .adapters import SETS
from .functions.columns import list_length
from .functions.weights import by_level, uniform
from .ontology import Ontology, dag_to_tree
from .operators import avg_join, baselines, bounds, emd_join, every_pair, extensions, measures, min_join
from .operators.distance import all_pairs, avg_distance, distance_matrix, emd_distance
from .operators.ordered_pairs import ordered_pairs
from .sql import LEAVES, counts_sql, distances_sql, key_sql, topk_sql

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, tuple[Query, str | None]] = {}
K = 10


def _add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = (query, sql)


# -- two sets: what users do on weekdays against weekends -----------------------------------------------------------------
def _two(run: Callable) -> Query:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        left, tree = SETS["weekday_activity"].load(spark, sf)
        return run(left, tree, SETS["weekend_activity"].objects(spark, sf))

    return query


_two_sql = lambda measure: topk_sql("weekday_activity", measure, K, "weekend_activity")
_add("emd_two_sets", _two(lambda o, t, r: emd_join.emd_topk(o, t, K, right=r)), _two_sql("emd"))
_add("emd_two_sets_progressive", _two(lambda o, t, r: emd_join.emd_topk(o, t, K, right=r, variant="l1_reduced", engine="progressive")), _two_sql("emd"))
_add("emd_two_sets_reduced_progressive", _two(lambda o, t, r: emd_join.emd_topk(o, t, K, right=r, variant="emd_reduced", engine="progressive")), _two_sql("emd"))
_add("emd_two_sets_brute_progressive", _two(lambda o, t, r: emd_join.emd_topk(o, t, K, right=r, variant="brute", engine="progressive")), _two_sql("emd"))
_add("avg_two_sets", _two(lambda o, t, r: avg_join.avgdist_topk(o, t, K, right=r)), _two_sql("avg"))
_add("avg_two_sets_progressive", _two(lambda o, t, r: avg_join.avgdist_topk(o, t, K, right=r, engine="progressive")), _two_sql("avg"))
_add("min_two_sets", _two(lambda o, t, r: min_join.mindist_topk(o, t, K, right=r)), _two_sql("min"))


# -- variants of the searches -----------------------------------------------------------------------------------------------
def _on(data: str, run: Callable) -> Query:
    return lambda spark, sf: run(*SETS[data].load(spark, sf))


_add("avg_topk_dfs", _on("user_activity", lambda o, t: avg_join.avgdist_topk(o, t, K, order="dfs", engine="progressive")), topk_sql("user_activity", "avg", K))
_add("avg_topk_progressive_complete", _on("user_activity", lambda o, t: avg_join.avgdist_topk(o, t, K, refine="complete", engine="progressive")), topk_sql("user_activity", "avg", K))
_add("emd_topk_progressive_edge", _on("user_activity", lambda o, t: emd_join.emd_topk(o, t, K, variant="edge", engine="progressive")), topk_sql("user_activity", "emd", K))
_add("emd_topk_progressive_l1full", _on("user_activity", lambda o, t: emd_join.emd_topk(o, t, K, variant="l1_full", engine="progressive")), topk_sql("user_activity", "emd", K))
_add("emd_topk_dedup_pages", _on("page_groups", lambda o, t: emd_join.emd_topk(o, t, K, dedupe=True)), topk_sql("page_groups", "emd", K))
_add("min_topk_pages", _on("page_groups", lambda o, t: min_join.mindist_topk(o, t, K)), topk_sql("page_groups", "min", K))


def _knn_min(spark: SparkSession, sf: str) -> DataFrame:
    o, tree = SETS["part_geo"].load(spark, sf)
    return extensions.knn(o, tree, o.filter("obj_id % 100 = 0"), 5, "min")


_add("min_knn", _knn_min, f"""
WITH {distances_sql('part_geo', 'min', 'part_geo', where="AND x.obj_id <> y.obj_id AND x.obj_id % 100 = 0")},
r AS (SELECT a AS query, row_number() OVER (PARTITION BY a ORDER BY dist, b) AS rank, b, dist FROM d)
SELECT query, CAST(rank AS INTEGER) AS rank, b, dist FROM r WHERE rank <= 5""")


def _multi(agg: str, weights: list[float] | None = None) -> Query:
    return lambda s, sf: extensions.multi_topk([SETS["customer_product"].load(s, sf), SETS["customer_days"].load(s, sf)], K, agg, weights=weights)


def _multi_sql(combined: str) -> str:
    return f"""
WITH p AS (WITH {distances_sql('customer_product', 'emd')} SELECT a, b, dist FROM d), t AS (WITH {distances_sql('customer_days', 'emd')} SELECT a, b, dist FROM d), d AS (SELECT p.a, p.b, {combined} AS dist FROM p JOIN t ON p.a = t.a AND p.b = t.b)
SELECT CAST(row_number() OVER (ORDER BY dist, a, b) AS INTEGER) AS rank, a, b, dist FROM d ORDER BY dist, a, b LIMIT {K}"""


_add("multi_ontology_max", _multi("max"), _multi_sql("greatest(p.dist, t.dist)"))
_add("multi_ontology_weighted", _multi("wavg", [1.0, 3.0]), _multi_sql("(CAST(1 AS DOUBLE) * p.dist + CAST(3 AS DOUBLE) * t.dist) / CAST(4 AS DOUBLE)"))


def _gap_values(spark: SparkSession, sf: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/supplier.parquet").select(F.col("s_nationkey").alias("dim"), F.col("s_suppkey").alias("id"), F.col("s_acctbal").cast("double").alias("value"))


_GAPS = """
WITH g AS (SELECT x.s_nationkey AS dim, least(x.s_suppkey, y.s_suppkey) AS a, greatest(x.s_suppkey, y.s_suppkey) AS b, abs(CAST(x.s_acctbal AS DOUBLE) - CAST(y.s_acctbal AS DOUBLE)) AS gap FROM supplier x JOIN supplier y ON x.s_nationkey = y.s_nationkey AND x.s_suppkey < y.s_suppkey),
r AS (SELECT *, row_number() OVER (PARTITION BY dim ORDER BY gap, a, b) AS nth FROM g) SELECT dim, CAST(nth AS INTEGER) AS nth, a, b, round(gap, 6) AS gap FROM r WHERE nth <= 5"""
for _init in ("sort", "hash"):
    _add(f"ordered_pairs_{_init}", lambda s, sf, init=_init: ordered_pairs(_gap_values(s, sf), 5, init).select("dim", "nth", "a", "b", F.round("gap", 6).alias("gap")), _GAPS)

# -- trees --------------------------------------------------------------------------------------------------------------
_NATIONS = "SELECT n_regionkey AS k1, n_nationkey AS k2 FROM nation"


def _nation_rows(spark: SparkSession, sf: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/nation.parquet").select(F.col("n_regionkey").alias("k1"), F.col("n_nationkey").alias("k2"))


def _weighted(rule) -> Query:
    return lambda s, sf: Ontology.from_levels(_nation_rows(s, sf), [F.col("k1"), F.col("k2")], rule).nodes.select("node_id", "parent_id", "level", "w", "depth")


def _weighted_sql(one: int, two: int) -> str:
    return f"""
WITH leaf AS ({_NATIONS}) SELECT 'root' AS node_id, CAST(NULL AS VARCHAR) AS parent_id, 0 AS level, CAST(0 AS BIGINT) AS w, CAST(0 AS BIGINT) AS depth
UNION ALL SELECT DISTINCT {key_sql(1)}, 'root', 1, CAST({one} AS BIGINT), CAST({one} AS BIGINT) FROM leaf
UNION ALL SELECT DISTINCT {key_sql(2)}, {key_sql(1)}, 2, CAST({two} AS BIGINT), CAST({one + two} AS BIGINT) FROM leaf"""


_add("ontology_uniform_weights", _weighted(uniform()), _weighted_sql(1, 1))
_add("ontology_level_weights", _weighted(by_level(["1.5", "0.25"])), _weighted_sql(6, 1))


def _unfold(spark: SparkSession, sf: str) -> DataFrame:
    """Nations below their region and below the region after it: each path from the root is a node."""
    n = spark.read.parquet(f"{sf}/nation.parquet")
    up = n.select(F.concat(F.lit("n"), "n_nationkey").alias("child"), F.explode(F.array(F.col("n_regionkey"), (F.col("n_regionkey") + 1) % 5)).alias("r"))
    r = spark.read.parquet(f"{sf}/region.parquet").select(F.concat(F.lit("r"), "r_regionkey").alias("child"), F.lit("root").alias("parent"))
    root = spark.range(1).select(F.lit("root").alias("child"), F.lit(None).cast("string").alias("parent"))
    return dag_to_tree(up.select("child", F.concat(F.lit("r"), "r").alias("parent")).unionByName(r).unionByName(root), "unfold")


_add("dag_unfold", _unfold, """
WITH up AS (SELECT n_nationkey AS n, unnest([n_regionkey, (n_regionkey + 1) % 5]) AS r FROM nation)
SELECT 'root' AS child, CAST(NULL AS VARCHAR) AS parent UNION ALL SELECT 'root/r' || r_regionkey, 'root' FROM region
UNION ALL SELECT 'root/r' || r || '/n' || n, 'root/r' || r FROM up""")


def _counts(found: dict[str, int], spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(found.items()), "fault string, n long")


def _validate(spark: SparkSession, sf: str) -> DataFrame:
    tree = SETS["part_geo"].ontology(spark, sf)
    return _counts(tree.validate(tree.nodes.select(F.col("node_id").alias("child"), F.col("parent_id").alias("parent"))), spark)


_add("ontology_validate", _validate, """
WITH n AS (SELECT 's' || s_suppkey AS node_id, 'n' || s_nationkey AS parent_id, 1 AS w FROM supplier
  UNION ALL SELECT 'n' || n_nationkey, 'r' || n_regionkey, 2 FROM nation UNION ALL SELECT DISTINCT 'r' || n_regionkey, 'root', 4 FROM nation UNION ALL SELECT 'root', NULL, 0)
SELECT 'roots_missing_or_extra' AS fault, abs(count(*) FILTER (WHERE parent_id IS NULL) - 1) AS n FROM n
UNION ALL SELECT 'repeated_nodes', count(*) FROM (SELECT node_id FROM n GROUP BY node_id HAVING count(*) > 1)
UNION ALL SELECT 'bad_weights', count(*) FROM n WHERE parent_id IS NOT NULL AND w <= 0
UNION ALL SELECT 'orphans', count(*) FROM n WHERE parent_id IS NOT NULL AND parent_id NOT IN (SELECT node_id FROM n)
UNION ALL SELECT 'overflow', count(*) FROM n WHERE w >= 4194304
UNION ALL SELECT 'unreached', count(*) FROM n WHERE node_id NOT IN (SELECT node_id FROM n)""")
_add("ontology_metric_check", lambda s, sf: _counts(Ontology.from_levels(_nation_rows(s, sf), [F.col("k1"), F.col("k2")]).check_metric(), s), f"""
WITH n AS (SELECT 0 AS lv, -1 AS r, -1 AS c UNION ALL SELECT DISTINCT 1, k1, -1 FROM ({_NATIONS}) UNION ALL SELECT 2, k1, k2 FROM ({_NATIONS})),
d AS (SELECT x.lv AS xl, x.r AS xr, x.c AS xc, y.lv AS yl, y.r AS yr, y.c AS yc,
  CASE WHEN x.c = y.c AND x.r = y.r THEN 0 WHEN x.r = y.r AND x.r >= 0 THEN (x.c >= 0)::INT + (y.c >= 0)::INT
  ELSE 2 * (x.lv > 0)::INT + (x.lv > 1)::INT + 2 * (y.lv > 0)::INT + (y.lv > 1)::INT END AS dist FROM n x CROSS JOIN n y)
SELECT 'symmetry' AS fault, count(*) AS n FROM d p JOIN d q ON p.xr = q.yr AND p.xc = q.yc AND p.yr = q.xr AND p.yc = q.xc WHERE p.dist <> q.dist
UNION ALL SELECT 'identity', count(*) FROM d WHERE (dist = 0) <> (xr = yr AND xc = yc)
UNION ALL SELECT 'triangle', count(*) FROM d p JOIN d q ON p.yr = q.xr AND p.yc = q.xc JOIN d s ON s.xr = p.xr AND s.xc = p.xc AND s.yr = q.yr AND s.yc = q.yc WHERE s.dist > p.dist + q.dist""")

# -- distances and bounds on every pair of a small set ----------------------------------------------------------------------
_PAGES_MATRIX = lambda m: f"""
WITH {distances_sql('page_groups', m, 'page_groups', where='AND x.obj_id <= y.obj_id')} SELECT a, b, dist FROM d"""  # noqa: E731
for _m in ("emd", "avg", "min"):
    _add(f"distance_matrix_{_m}", _on("page_groups", lambda o, t, m=_m: distance_matrix(o, t, m)), _PAGES_MATRIX(_m))
for _m in ("avg", "min"):
    _add(f"naive_{_m}", _on("page_groups", lambda o, t, m=_m: every_pair.naive(o, t, m)), f"WITH {distances_sql('page_groups', _m)} SELECT a, b, dist FROM d")
_add("avg_reduced_pairs", _on("user_activity", lambda o, t: every_pair.avg_reduced(o, t, 1)), f"WITH {distances_sql('user_activity', 'avg', upto=1)} SELECT a, b, dist AS bound FROM d")
_add("residual_depth", _on("part_geo", lambda o, t: bounds.residual_depth(o, t, 1)), f"WITH leaf AS ({LEAVES['part_geo'][0]}) SELECT obj_id, CAST(sum(3) AS DOUBLE) / CAST(4 * count(*) AS DOUBLE) AS residual FROM leaf GROUP BY obj_id")
_add("pivot_band", _on("page_groups", lambda o, t: bounds.pivot_band(o, t, 0.5)), f"WITH leaf AS ({LEAVES['page_groups'][0]}), m AS (SELECT obj_id, CAST(sum(7) AS DOUBLE) / CAST(4 * count(*) AS DOUBLE) AS m FROM leaf GROUP BY obj_id) SELECT x.obj_id AS a, y.obj_id AS b, abs(x.m - y.m) AS bound FROM m x JOIN m y ON x.obj_id < y.obj_id WHERE abs(x.m - y.m) <= 0.5")
_add("avg_descend_level_1", _on("user_activity", lambda o, t: every_pair.avg_descend(o, t, 1)), f"""
WITH {counts_sql('user_activity')}, ch AS (SELECT obj_id, '1:' || CAST(k1 AS VARCHAR) AS node, count(*) AS k, min(k2) AS only FROM leaf GROUP BY ALL),
t AS (SELECT ch.obj_id, ch.node, c.c, c.c * c.below AS d, ch.k, ch.only FROM ch JOIN c ON c.obj_id = ch.obj_id AND c.node = ch.node AND c.lv = 1),
s AS (SELECT x.obj_id AS a, y.obj_id AS b, CAST(sum(2 * 2 * x.c * y.c + y.c * x.d + x.c * y.d
  - CASE WHEN x.k = 1 AND y.k = 1 AND x.only = y.only THEN 0 WHEN x.k = 1 AND y.k = 1 THEN y.c * x.d + x.c * y.d WHEN x.k = 1 THEN x.d WHEN y.k = 1 THEN y.d ELSE x.d + y.d END) AS BIGINT) AS s
  FROM t x JOIN t y ON x.node = y.node AND x.obj_id < y.obj_id GROUP BY 1, 2)
SELECT x.obj_id AS a, y.obj_id AS b, CAST(6 * x.n * y.n - coalesce(s.s, 0) AS DOUBLE) / CAST(2 * x.n * y.n AS DOUBLE) AS bound
FROM sz x JOIN sz y ON x.obj_id < y.obj_id LEFT JOIN s ON s.a = x.obj_id AND s.b = y.obj_id""")
_add("avg_descend_level_2", _on("user_activity", lambda o, t: every_pair.avg_descend(o, t, 2)), f"WITH {distances_sql('user_activity', 'avg')} SELECT a, b, dist AS bound FROM d")


# -- measures -------------------------------------------------------------------------------------------------------------
def _short_lists_sql(k: int) -> str:
    """The published list length, replayed: pairs of the first objects of each node, against the exact answers."""
    m = list_length(k, "sqrt")
    return f"""
WITH {counts_sql('part_geo')}, near AS (SELECT node, obj_id, below AS dist FROM c UNION ALL SELECT 'root', obj_id, 7 FROM sz),
l AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY dist, obj_id) AS nth FROM near QUALIFY nth <= {m}),
g AS (SELECT least(x.obj_id, y.obj_id) AS a, greatest(x.obj_id, y.obj_id) AS b, min(x.dist + y.dist) AS d FROM l x JOIN l y ON x.node = y.node AND x.nth < y.nth GROUP BY 1, 2),
got AS (SELECT a, b, CAST(d AS DOUBLE) / 4 AS dist FROM g ORDER BY d, a, b LIMIT {k}),
f AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY dist, obj_id) AS nth FROM near QUALIFY nth <= {k + 1}),
h AS (SELECT least(x.obj_id, y.obj_id) AS a, greatest(x.obj_id, y.obj_id) AS b, min(x.dist + y.dist) AS d FROM f x JOIN f y ON x.node = y.node AND x.nth < y.nth GROUP BY 1, 2),
want AS (SELECT a, b, CAST(d AS DOUBLE) / 4 AS dist FROM h ORDER BY d, a, b LIMIT {k})
SELECT (SELECT count(*) FROM want) AS k, CAST((SELECT count(*) FROM got JOIN want USING (a, b)) AS DOUBLE) / (SELECT count(*) FROM want) AS precision,
  coalesce((SELECT max(dist) FROM got), 0) - (SELECT max(dist) FROM want) AS kth_error"""


def _sqrt(spark: SparkSession, sf: str) -> DataFrame:
    o, tree = SETS["part_geo"].load(spark, sf)
    return measures.agreement(min_join.mindist_topk(o, tree, K, list_len="sqrt"), min_join.mindist_topk(o, tree, K))


_add("agreement_short_lists", _sqrt, _short_lists_sql(K))
_add("agreement_brute_force", _on("user_activity", lambda o, t: measures.agreement(emd_join.emd_topk(o, t, K), baselines.brute_force(o, t, "emd", K, engine="join"))), f"""
WITH {distances_sql('user_activity', 'emd')}, w AS (SELECT * FROM d ORDER BY dist, a, b LIMIT {K}) SELECT count(*) AS k, CAST(1 AS DOUBLE) AS precision, max(dist) - max(dist) AS kth_error FROM w""")


def _seconds(spark: SparkSession, sf: str) -> DataFrame:
    """measure, pairs, ms: time per distance of the transport problem, the closed form and half L1, on every pair of a set."""
    o, tree = SETS["page_groups"].load(spark, sf)
    o = o.persist()
    p = all_pairs(o).persist()
    n, rows = p.count(), []
    runs = {"emd as a transport problem": lambda: emd_distance(p, o, tree, solver="flow"), "emd by the closed form": lambda: emd_distance(p, o, tree), "half L1": lambda: bounds.l1_reduced(p, o, tree), "avg": lambda: avg_distance(p, o, tree)}
    for name, run in runs.items():
        began = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        rows.append((name, n, 1000 * (time.perf_counter() - began) / max(n, 1)))
    p.unpersist()
    o.unpersist()
    return spark.createDataFrame(rows, "measure string, pairs long, ms double")


_add("time_per_distance", _seconds)


def _quality(measure: str) -> Query:
    """Answers of the k closest pairs within one language, over the first 59 documents of each of two languages."""

    def query(spark: SparkSession, sf: str) -> DataFrame:
        lang = spark.read.parquet(f"{sf}/documents.parquet").select(F.col("doc_id").alias("obj_id"), F.col("lang").alias("category"))
        first = [lang.filter(F.col("category") == c).orderBy("obj_id").limit(59) for c in ("de", "en")]
        o, tree = SETS["doc_words"].load(spark, sf)
        o = o.join(F.broadcast(first[0].unionByName(first[1]).select("obj_id")), "obj_id")
        search = {"emd": emd_join.emd_topk, "avg": avg_join.avgdist_topk, "min": min_join.mindist_topk}[measure]
        return measures.purity(search(o, tree, 50), lang)

    return query


def _quality_sql(measure: str) -> str:
    leaf = f"SELECT w.* FROM ({LEAVES['doc_words'][0]}) w WHERE obj_id IN (SELECT doc_id FROM (SELECT doc_id, row_number() OVER (PARTITION BY lang ORDER BY doc_id) AS nth FROM documents WHERE lang IN ('de', 'en')) WHERE nth <= 59)"
    return f"""
WITH t AS ({topk_sql('doc_words', measure, 50).replace(LEAVES['doc_words'][0], leaf)}), j AS (SELECT t.rank, x.lang = y.lang AS same FROM t JOIN documents x ON t.a = x.doc_id JOIN documents y ON t.b = y.doc_id)
SELECT cut, count(*) AS pairs, count(*) FILTER (WHERE same) AS same FROM j JOIN (VALUES (10), (50)) v(cut) ON rank <= cut GROUP BY cut"""


for _m in ("emd", "avg", "min"):
    _add(f"quality_{_m}", _quality(_m), _quality_sql(_m))
