"""Sources, generator, streaming, planner, SQL surface, registry."""

import random

import pytest
from pyspark.sql import functions as F

from treepairs.adapters import SETS
from treepairs.ontology import Ontology
from treepairs.operators import min_join
from treepairs.plans import planner
from treepairs.sources import files, synth
from treepairs.sql import closure_sql, register
from treepairs.streaming.windows import GrowingMinTopK, best_of_windows, distinct_events, sessions, weekly_terms, windowed_counts

SF = "/root/testdata/sf0.001"


def test_generator(spark):
    t = synth.ontology(spark, 300, top=7)
    assert t.size() == 300 and set(t.validate().values()) == {0} and t.nodes.filter("level = 1").count() == 7
    o = synth.objects(spark, 50, 300, 6.0)
    n = [r.n for r in o.groupBy("obj_id").agg(F.count(F.lit(1)).alias("n")).collect()]
    assert len(n) == 50 and 3 <= min(n) and max(n) <= 9 and o.distinct().count() == o.count()
    assert sorted(map(tuple, o.collect())) == sorted(map(tuple, synth.objects(spark, 50, 300, 6.0).repartition(3).collect()))


def test_generator_as_a_source(spark):
    synth.register_source(spark)
    e = spark.read.format("synthtree").option("terms", 100).option("partitions", 3).load()
    assert Ontology.from_edges(e).size() == 100


def test_files(spark, tmp_path):
    (tmp_path / "e.csv").write_text("child,parent\nr,\na,r\nb,r\n")
    assert {tuple(r) for r in files.read_edges(spark, str(tmp_path / "e.csv")).collect()} == {("r", None), ("a", "r"), ("b", "r")}
    (tmp_path / "e.json").write_text('{"child":"r"}\n{"child":"a","parent":"r"}\n')
    assert files.read_edges(spark, str(tmp_path / "e.json"), "json").count() == 2
    (tmp_path / "v.obo").write_text("header\n[Term]\nid: X:1\nname: top\n\n[Term]\nid: X:2\nis_a: X:1 ! top\nrelationship: part_of X:3\n\n[Term]\nid: X:3\nis_a: X:1\n")
    assert {tuple(r) for r in files.read_stanzas(spark, str(tmp_path / "v.obo")).collect()} == {("X:1", None), ("X:2", "X:1"), ("X:2", "X:3"), ("X:3", "X:1")}
    o, t = SETS["user_activity"].load(spark, SF)
    files.write_answers(min_join.mindist_topk(o, t, 5), str(tmp_path / "out"), 2)
    assert spark.read.parquet(str(tmp_path / "out")).select("rank_bucket").distinct().count() == 3


def test_sql_surface(spark):
    o, t = SETS["part_geo"].load(spark, SF)
    register(spark, o, t.nodes)
    got = spark.sql("SELECT node_distance(x.path, y.path) AS d FROM tree_nodes x, tree_nodes y WHERE x.parent_id = y.node_id AND x.level = 1").collect()
    assert {r.d for r in got} == {4}
    term = o.first().term_id
    assert spark.sql(f"SELECT * FROM objects_with('{term}')").count() == o.filter(F.col("term_id") == term).count()
    assert sorted(map(tuple, closure_sql(spark, t.nodes).collect())) == sorted(map(tuple, t.closure().select("node_id", "anc_id", "anc_level", "dist").collect()))


def test_growing_set(spark, tmp_path):
    o, t = SETS["user_activity"].load(spark, SF)
    rows = o.collect()
    random.Random(1).shuffle(rows)
    g = GrowingMinTopK(t, 6)
    for i in range(0, len(rows), 300):
        g.add(spark.createDataFrame(rows[i : i + 300], o.schema))
    want = min_join.mindist_topk(o, t, 6).collect()
    assert g.answer().collect() == want
    spark.createDataFrame(rows, o.schema).repartition(3).write.parquet(str(tmp_path / "in"))
    s = GrowingMinTopK(t, 6)
    s.run(spark.readStream.schema(o.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")), str(tmp_path / "cp")).awaitTermination()
    assert s.answer().collect() == want


def test_windows_of_a_stream(spark, tmp_path):
    e = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    e.repartition(4).write.parquet(str(tmp_path / "in"))
    stream = lambda: spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    for name, f in {"w": lambda s: windowed_counts(s, "400 days"), "s": lambda s: sessions(s, watermark="400 days"), "d": lambda s: distinct_events(s, "400 days")}.items():
        q = f(stream()).writeStream.format("memory").queryName(f"m_{name}").outputMode("append" if name == "d" else "complete" if name == "w" else "append").option("checkpointLocation", str(tmp_path / f"cp{name}")).trigger(availableNow=True).start()
        q.awaitTermination()
    assert {(r.win, r.event_type, r.n) for r in spark.table("m_w").collect()} == {(r.win, r.event_type, r.n) for r in windowed_counts(e).collect()}
    assert spark.table("m_d").count() == e.count()
    assert best_of_windows(weekly_terms(e), 2).filter("rank = 1").count() > 1


def test_planner(spark):
    o, t = SETS["part_geo"].load(spark, SF)
    s = planner.statistics(o, t)
    assert s.height == 3 and planner.choose(s, "min").engine == "closure" and planner.choose(s, "emd").bound_height >= 1
    assert planner.pair_work(s)[1] >= planner.pair_work(s)[3]


def test_registry(spark):
    import __spark_entry__ as entry

    names, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(names) and len(names) > 80
    df = entry.entry(spark)
    assert df.columns == ["rank", "a", "b", "dist"] and df.count() == 10


@pytest.mark.parametrize("name", ["emd_topk_parts_geo", "min_topk_parts_geo", "avg_topk_customers_product", "emd_knn_parts", "stream_topk_windows", "window_frames", "joins_as_of", "subtree_counts_rollup"])
def test_sql_twins(spark, name):
    import duckdb

    import __spark_entry__ as entry

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    got = entry.queries()[name](spark, SF)
    cols = ", ".join(f'"{c}"' for c in got.columns)
    want = con.execute(f"SELECT {cols} FROM ({entry.oracle_sql()[name]})").fetchall()
    assert sorted(map(repr, (tuple(r) for r in got.collect()))) == sorted(map(repr, want)) and want
