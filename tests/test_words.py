"""Searches over sets of words, against the search on the tree of the words."""

import random

import pytest
from pyspark.sql import functions as F

from treepairs.ontology import Ontology, node_key
from treepairs.operators import emd_join, streamed, worded
from treepairs.operators.objects import annotate

LETTERS = "aábc"


def texts(n, seed, copies=0):
    r = random.Random(seed)
    rows = [(i, " ".join("".join(r.choice(LETTERS) for _ in range(r.randint(1, 5))) for _ in range(r.randint(1, 12)))) for i in range(n)]
    return rows + [(n + i, rows[i % 2][1].upper() + " " + rows[i % 2][1]) for i in range(copies)]


def made(spark, rows):
    t = spark.createDataFrame(rows, "id long, text string")
    w = worded.words(t, F.col("id"), F.col("text"))
    return w, w.select("obj_id", F.explode("terms").alias("k4")).select("obj_id", *[F.substring("k4", 1, i).alias(f"k{i}") for i in (1, 2, 3)], "k4")


def on_tree(leaves, k, right=None):
    levels = [F.col(f"k{i}") for i in range(1, 5)]
    both = leaves if right is None else leaves.unionByName(right)
    objects = lambda x: annotate(x, F.col("obj_id"), node_key(levels))
    return emd_join.emd_topk(objects(leaves), Ontology.from_levels(both.drop("obj_id"), levels), k, right=None if right is None else objects(right))


def rows(df):
    return [tuple(r) for r in df.orderBy("rank").collect()]


def refuse():
    raise AssertionError("the general search was asked")


def test_words_of_repeated_and_missing_ids(spark):
    w, _ = made(spark, [(1, "B a, a"), (1, "c A"), (2, None), (None, "a"), (3, "12 -"), (4, "é1b")])
    assert sorted(map(tuple, w.collect())) == [(1, ["a", "b", "c"]), (4, ["b", "é"])]


def test_equal_objects_answer_alone(spark):
    w, leaves = made(spark, texts(30, 1, copies=6))
    got = rows(worded.emd_topk(w, 10, refuse))
    assert got == rows(on_tree(leaves, 10)) and {r[3] for r in got} == {0.0}
    most = 12 + 40  # more pairs than there are at 0
    assert rows(worded.emd_topk(w, most, lambda: on_tree(leaves, most))) == rows(on_tree(leaves, most))


@pytest.mark.parametrize("sent", [2_000_000, 400])
def test_two_sets_need_the_nodes_of_the_small_one_only(spark, monkeypatch, sent):
    """With 400 nodes only the left side is small enough to be sent."""
    few, many = texts(8, 2), texts(90, 3, copies=5)
    monkeypatch.setattr(streamed, "SENT_NODES", sent)
    (x, lx), (y, ly) = made(spark, few), made(spark, many)
    for left, right, ll, lr in ((x, y, lx, ly), (y, x, ly, lx)):
        assert rows(worded.emd_topk(left, 15, refuse, right)) == rows(on_tree(ll, 15, lr))


def test_two_large_sets_take_the_general_search(spark, monkeypatch):
    monkeypatch.setattr(streamed, "SENT_NODES", 3)
    (x, lx), (y, ly) = made(spark, texts(8, 4)), made(spark, texts(9, 5))
    assert rows(worded.emd_topk(x, 5, lambda: on_tree(lx, 5, ly), y)) == rows(on_tree(lx, 5, ly))


@pytest.mark.parametrize("name", ["emd_topk_docs_lexical", "purity_topk", "emd_bipartite_docs_benchmark"])
def test_registered_queries_make_no_tree(spark, monkeypatch, name):
    import __spark_entry__ as entry

    monkeypatch.setattr(Ontology, "from_levels", staticmethod(lambda *_: refuse()))
    assert entry.queries()[name](spark, "/root/testdata/sf0.01").count() in (2, 10)
