"""SQL texts: the closed forms as queries for a second engine, and table functions for Spark SQL.

Every levelled set is a query with obj_id and k1, k2, ..; distances follow from grouped counts by level, all pairs of
sizes and one division, so the numbers agree to the last bit with those of the engine.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

_GEO = "SELECT {obj} AS obj_id, n_regionkey AS k1, n_nationkey AS k2, l_suppkey AS k3 FROM (SELECT DISTINCT {obj}, l_suppkey FROM lineitem) JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey"
_WORDS = "SELECT obj_id, substr(k4, 1, 1) AS k1, substr(k4, 1, 2) AS k2, substr(k4, 1, 3) AS k3, k4 FROM (SELECT DISTINCT {obj} AS obj_id, unnest(regexp_extract_all(lower(coalesce(text, '')), '\\p{{L}}+')) AS k4 FROM {table})"
_BITS = "list_aggregate(list_transform(embedding[{a}:{b}], lambda x: CASE WHEN x >= 0 THEN '1' ELSE '0' END), 'string_agg', '')"

#: name: (query of distinct leaf rows, number of levels)
LEAVES: dict[str, tuple[str, int]] = {
    "part_geo": (_GEO.format(obj="l_partkey"), 3),
    "order_geo": (_GEO.format(obj="l_orderkey"), 3),
    "customer_product": ("SELECT DISTINCT o_custkey AS obj_id, p_type AS k1, p_brand AS k2 FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey", 2),
    "supplier_product": ("SELECT DISTINCT l_suppkey AS obj_id, p_type AS k1, p_brand AS k2 FROM lineitem JOIN part ON l_partkey = p_partkey", 2),
    "part_product": ("SELECT p_partkey AS obj_id, p_type AS k1, p_brand AS k2 FROM part", 2),
    "user_activity": ("SELECT DISTINCT user_id AS obj_id, event_type AS k1, hour(ts) AS k2 FROM events", 2),
    "weekday_activity": ("SELECT DISTINCT user_id AS obj_id, event_type AS k1, hour(ts) AS k2 FROM events WHERE dayofweek(ts) NOT IN (0, 6)", 2),
    "weekend_activity": ("SELECT DISTINCT user_id AS obj_id, event_type AS k1, hour(ts) AS k2 FROM events WHERE dayofweek(ts) IN (0, 6)", 2),
    "customer_days": ("SELECT DISTINCT o_custkey AS obj_id, year(o_orderdate) AS k1, month(o_orderdate) AS k2, day(o_orderdate) AS k3 FROM orders", 3),
    "part_market": ("SELECT DISTINCT l_partkey AS obj_id, c_mktsegment AS k1, c_nationkey AS k2 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey", 2),
    "doc_words": (_WORDS.format(obj="doc_id", table="documents"), 4),
    "benchmark_words": (_WORDS.format(obj="item_id", table="benchmark"), 4),
    "page_groups": ("SELECT DISTINCT page_id // 5 AS obj_id, regexp_extract(url, '://[^/?#]*\\.([^./?#:]+)', 1) AS k1, regexp_extract(url, '://([^/?#:]+)', 1) AS k2, split_part(regexp_extract(url, '://[^/?#]+([^?#]*)', 1), '/', 2) AS k3 FROM pages", 3),
    "vector_groups": (f"SELECT DISTINCT vec_id // 5 AS obj_id, label AS k1, {_BITS.format(a=1, b=3)} AS k2, {_BITS.format(a=4, b=6)} AS k3 FROM embeddings", 3),
}


def key_sql(n: int) -> str:
    return f"'{n}:' || concat_ws('/', " + ", ".join(f"CAST(k{i} AS VARCHAR)" for i in range(1, n + 1)) + ")"


def counts_sql(name: str, tag: str = "", upto: int | None = None) -> str:
    """CTEs leaf, sz (obj_id, n) and c (obj_id, lv, node, w, below, c) of a set; the names end in ``tag``."""
    query, height = LEAVES[name]
    levels = " UNION ALL ".join(
        f"SELECT obj_id, {lv} AS lv, {key_sql(lv)} AS node, CAST({2 ** (height - lv)} AS BIGINT) AS w, CAST({2 ** (height - lv) - 1} AS BIGINT) AS below, count(*) AS c FROM leaf{tag} GROUP BY ALL" for lv in range(1, (upto or height) + 1)
    )
    return f"leaf{tag} AS ({query}), sz{tag} AS (SELECT obj_id, count(*) AS n FROM leaf{tag} GROUP BY obj_id), c{tag} AS ({levels})"


def scale_of(name: str) -> tuple[int, int, int]:
    """(height, scale, scaled depth of a leaf)"""
    h = LEAVES[name][1]
    return h, 2 ** (h - 1), 2**h - 1


def distances_sql(name: str, measure: str, right: str | None = None, upto: int | None = None, where: str = "", where_right: str = "") -> str:
    """CTEs ending in ``d`` (a, b, na, nb, dist) over all pairs."""
    height, scale, depth = scale_of(name)
    depth = sum(2 ** (height - lv) for lv in range(1, (upto or height) + 1)) if upto else depth
    other = "_r" if right else ""
    ctes = [counts_sql(name, "", upto)] + ([counts_sql(right, "_r", upto)] if right else [])
    on = "TRUE" if right else "x.obj_id < y.obj_id"
    pairs = f"p AS (SELECT x.obj_id AS a, y.obj_id AS b, x.n AS na, y.n AS nb FROM sz x JOIN sz{other} y ON {on} {where})"
    if measure == "min":
        shared = f"s AS (SELECT p.a, p.b, min(x.below + y.below) AS s FROM p JOIN c x ON x.obj_id = p.a JOIN c{other} y ON y.obj_id = p.b AND x.node = y.node GROUP BY p.a, p.b)"
        dist = f"CAST(coalesce(s, {2 * depth}) AS DOUBLE) / {scale}"
    else:
        term = "x.w * least(x.c * y.n, y.c * x.n)" if measure == "emd" else "x.w * x.c * y.c"
        left = "(SELECT c.*, sz.n FROM c JOIN sz USING (obj_id))"
        rgt = f"(SELECT c{other}.*, sz{other}.n FROM c{other} JOIN sz{other} USING (obj_id))"
        shared = f"s AS (SELECT x.obj_id AS a, y.obj_id AS b, CAST(sum({term}) AS BIGINT) AS s FROM {left} x JOIN {rgt} y ON x.node = y.node AND {on} {where} GROUP BY 1, 2)"
        dist = f"CAST({2 * depth} * na * nb - 2 * coalesce(s, 0) AS DOUBLE) / CAST({scale} * na * nb AS DOUBLE)"
    return ", ".join([*ctes, pairs, shared, f"d AS (SELECT p.a, p.b, na, nb, {dist} AS dist FROM p LEFT JOIN s ON p.a = s.a AND p.b = s.b)"])


def topk_sql(name: str, measure: str, k: int, right: str | None = None) -> str:
    return f"WITH {distances_sql(name, measure, right)} SELECT CAST(row_number() OVER (ORDER BY dist, a, b) AS INTEGER) AS rank, a, b, dist FROM d ORDER BY dist, a, b LIMIT {k}"


def range_sql(name: str, measure: str, radius: float, right: str | None = None) -> str:
    return f"WITH {distances_sql(name, measure, right)} SELECT a, b, dist FROM d WHERE dist <= {radius}"


def knn_sql(name: str, measure: str, k: int, queries: str) -> str:
    """``queries``: a condition on ``x.obj_id``."""
    height, scale, depth = scale_of(name)
    term = "x.w * least(x.c * y.n, y.c * x.n)" if measure == "emd" else "x.w * x.c * y.c"
    return (
        f"WITH {counts_sql(name)}, p AS (SELECT x.obj_id AS a, y.obj_id AS b, x.n AS na, y.n AS nb FROM sz x JOIN sz y ON x.obj_id <> y.obj_id WHERE {queries}), "
        f"cn AS (SELECT c.*, sz.n FROM c JOIN sz USING (obj_id)), "
        f"s AS (SELECT x.obj_id AS a, y.obj_id AS b, CAST(sum({term}) AS BIGINT) AS s FROM cn x JOIN cn y ON x.node = y.node WHERE {queries} GROUP BY 1, 2), "
        f"d AS (SELECT p.a, p.b, CAST({2 * depth} * na * nb - 2 * coalesce(s, 0) AS DOUBLE) / CAST({scale} * na * nb AS DOUBLE) AS dist FROM p LEFT JOIN s ON p.a = s.a AND p.b = s.b), "
        "r AS (SELECT a AS query, row_number() OVER (PARTITION BY a ORDER BY dist, b) AS rank, b, dist FROM d) SELECT query, CAST(rank AS INTEGER) AS rank, b, dist FROM r WHERE rank <= " + str(k)
    )


def register(spark: SparkSession, objects: DataFrame, nodes: DataFrame) -> None:
    """Views ``objects`` and ``tree_nodes`` and the SQL functions ``node_distance`` and ``inverted_list`` over them."""
    objects.createOrReplaceTempView("objects")
    nodes.createOrReplaceTempView("tree_nodes")
    spark.sql("""
        CREATE OR REPLACE TEMPORARY FUNCTION node_distance(p ARRAY<STRUCT<node_id: STRING, level: INT, w: BIGINT, depth: BIGINT>>, q ARRAY<STRUCT<node_id: STRING, level: INT, w: BIGINT, depth: BIGINT>>)
        RETURNS BIGINT RETURN element_at(p, -1).depth + element_at(q, -1).depth - 2 * array_max(zip_with(p, q, (x, y) -> CASE WHEN x.node_id = y.node_id THEN x.depth END))""")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION objects_with(term STRING) RETURNS TABLE (obj_id BIGINT) RETURN SELECT o.obj_id FROM objects o WHERE o.term_id = term")


def closure_sql(spark: SparkSession, nodes: DataFrame) -> DataFrame:
    """The ancestor closure by a recursive query over (node_id, parent_id, level, w)."""
    nodes.select("node_id", "parent_id", "level", "w").createOrReplaceTempView("closure_nodes")
    return spark.sql("""
        WITH RECURSIVE up(node_id, anc_id, anc_level, dist) AS (
          SELECT node_id, node_id, level, CAST(0 AS BIGINT) FROM closure_nodes
          UNION ALL
          SELECT u.node_id, n.parent_id, n.level - 1, u.dist + n.w FROM up u JOIN closure_nodes n ON u.anc_id = n.node_id WHERE n.parent_id IS NOT NULL)
        SELECT node_id, anc_id, anc_level, dist FROM up""")
