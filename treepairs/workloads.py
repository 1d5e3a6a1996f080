"""The experiments on the generator and the given tables; each returns rows that show a trend.

``python -m treepairs.workloads NAME [sf_dir]`` prints one; without a name all are run.
"""

from __future__ import annotations

import json
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .adapters import SETS
from .ontology import Ontology
from .operators import avg_join, baselines, bounds, emd_join, extensions, measures, min_join
from .operators.objects import avg_build, dedupe_objects
from .operators.search import Metrics
from .sources import synth

Row = dict
#: Stand-ins for the three real sets: terms and objects as published, branching and sizes by default.
REAL = {"process": (13_762, 3_437), "function": (7_803, 1_958), "localization": (1_990, 645)}


def timed(run: Callable[[], DataFrame]) -> tuple[float, int]:
    began = time.perf_counter()
    n = len(run().collect())
    return round(time.perf_counter() - began, 3), n


def made(spark: SparkSession, terms: int, n: int, size: float = 6.0, top: int | None = None, branching: float = 5.0, seed: int = 42) -> tuple[DataFrame, Ontology]:
    tree = synth.ontology(spark, terms, branching, top=top, seed=seed)
    o = synth.objects(spark, n, terms, size, seed=seed)
    return o.cache(), Ontology(tree.nodes.cache(), tree.scale, tree.height, tree.least_edge, tree.least_top_edge)


def emd_by_k(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    for name, load in {"users": lambda: SETS["user_activity"].load(spark, sf), "localization": lambda: made(spark, *REAL["localization"])}.items():
        o, t = load()
        for k in (1, 10, 50, 100):
            m = Metrics()
            s, _ = timed(lambda o=o, t=t, k=k, m=m: emd_join.emd_topk(o, t, k, metrics=m))
            out.append({"set": name, "k": k, "seconds": s, "bounds": m.pairs("bounds"), "exact": m.pairs("exact")})
    return out


def emd_by_n(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    for n in (50, 100, 250):
        o, t = made(spark, 1_990, n, 2.0, top=20)  # few terms, many subtrees: where the bound can prune
        r = measures.eta_emd(o, t, 10).first()
        b = timed(lambda o=o, t=t: baselines.brute_force(o, t, "emd", 10, engine="flow"))[0] if n <= 100 else None
        out.append({"n": n, "seconds": timed(lambda o=o, t=t: emd_join.emd_topk(o, t, 10))[0], "eta": round(r.eta, 4), "emd": r.emd, "l1": r.bounds, "full_l1": r.full_l1, "flow_brute_seconds": b})
    return out


def emd_by_terms(spark: SparkSession, sf: str) -> list[Row]:
    return [{"terms": terms, "seconds": timed(lambda t=made(spark, terms, 350, top=10): emd_join.emd_topk(*t, 10))[0]} for terms in (1_000, 10_000, 50_000)]


def emd_by_dimensions(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    for top in (2, 5, 10, 20):
        o, t = made(spark, 2_000, 150, 2.0, top=top)
        row: Row = {"dimensions": top + 1}
        for v in ("l1_reduced", "emd_reduced", "l1_full", "edge"):
            began = time.perf_counter()
            r = measures.eta_emd(o, t, 10, v).first()
            row |= {f"{v}_eta": round(r.eta, 4), f"{v}_seconds": round(time.perf_counter() - began, 3), f"{v}_bounds": r.bounds}
        out.append(row)
    return out


def min_by_k(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    for name, (terms, n) in REAL.items():
        o, t = made(spark, terms, n)
        timed(lambda o=o, t=t: min_join.mindist_topk(o, t, 1))
        out += [{"set": name, "k": k, "seconds": timed(lambda o=o, t=t, k=k: min_join.mindist_topk(o, t, k))[0]} for k in (1, 10, 50, 100)]
    return out


def min_by_terms(spark: SparkSession, sf: str) -> list[Row]:
    return [{"terms": terms, "seconds": timed(lambda t=made(spark, terms, 50_000): min_join.mindist_topk(*t, 100))[0]} for terms in (1_000, 10_000, 100_000)]


def min_by_n(spark: SparkSession, sf: str) -> list[Row]:
    return [{"n": n, "seconds": timed(lambda t=made(spark, 10_000, n): min_join.mindist_topk(*t, 10))[0]} for n in (1_000, 10_000, 100_000)]


def avg_by_k(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    for name in ("process", "function"):
        o, t = made(spark, *REAL[name], 3.0)
        out.append({"set": name, "k": 0, "build_seconds": timed(lambda o=o, t=t: avg_build(o, t).agg(F.sum("w")))[0]})
        for k in (1, 10, 100):
            out.append({"set": name, "k": k} | {r: timed(lambda o=o, t=t, k=k, r=r: avg_join.avgdist_topk(o, t, k, refine=r))[0] for r in ("stepwise", "complete")})
    return out


def avg_eta_by_k(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    o, t = made(spark, 1_990, 300, 2.0, top=10)
    for k in (1, 10, 100):
        row: Row = {"k": k}
        for r in ("stepwise", "complete"):
            m = measures.eta_avg(o, t, k, r).first()
            row |= {f"{r}_completed": round(m.eta, 4), f"{r}_examined": round(m.examined / m.pairs, 4)}
        out.append(row)
    return out


def avg_by_n(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    for n in (50, 100, 200):
        o, t = made(spark, 1_990, n, 2.0, top=10)
        m = measures.eta_avg(o, t, 10).first()
        out.append({"n": n, "examined": m.examined, "completed": m.complete})
    return out


def build_by_n_and_terms(spark: SparkSession, sf: str) -> list[Row]:
    return [{"n": n, "terms": terms, "build_seconds": timed(lambda t=made(spark, terms, n): avg_build(*t).agg(F.sum("w")))[0]} for terms in (1_000, 10_000) for n in (10_000, 100_000)]


def avg_by_terms(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    for terms in (500, 2_000, 8_000):
        m = measures.eta_avg(*made(spark, terms, 150, 2.0, top=10), 10).first()
        out.append({"terms": terms, "examined": m.examined, "completed": m.complete})
    return out


def quality(spark: SparkSession, sf: str) -> list[Row]:
    """59 documents of each of two languages on the word tree: answers within one language, and MIN's zero distances."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    lang = docs.select(F.col("doc_id").alias("obj_id"), F.col("lang").alias("category"))
    first = None
    for c in ("de", "en"):
        ids = lang.filter(F.col("category") == c).orderBy("obj_id").limit(59)
        first = ids if first is None else first.unionByName(ids)
    o, t = SETS["doc_words"].load(spark, sf)
    o = o.join(F.broadcast(first.select("obj_id")), "obj_id").cache()
    out = [{"measure": "min", "zero_pairs": measures.zero_pairs(o).first()[0]}]
    for name, run in {"emd": lambda: emd_join.emd_topk(o, t, 50), "avg": lambda: avg_join.avgdist_topk(o, t, 50), "min": lambda: min_join.mindist_topk(o, t, 50)}.items():
        out += [{"measure": name, "cut": r.cut, "same": r.same} for r in measures.purity(run(), lang).orderBy("cut").collect()]
    return out


def curation(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    for name in ("order_geo", "order_nation"):
        o = SETS[name].objects(spark, sf)
        out.append({"set": name, "objects": o.select("obj_id").distinct().count(), "distinct": dedupe_objects(o)[0].select("obj_id").distinct().count()})
    return out


def brute_comparison(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    for data in ("part_geo", "customer_product"):
        o, t = SETS[data].load(spark, sf)
        o = o.cache()
        runs = {"emd": lambda: emd_join.emd_topk(o, t, 10), "emd_l1_full": lambda: emd_join.emd_topk(o, t, 10, variant="l1_full"), "emd_l1_reduced": lambda: emd_join.emd_topk(o, t, 10, variant="l1_reduced"), "emd_brute": lambda: baselines.brute_force(o, t, "emd", 10), "min": lambda: min_join.mindist_topk(o, t, 10), "min_brute": lambda: baselines.brute_force(o, t, "min", 10), "avg": lambda: avg_join.avgdist_topk(o, t, 10), "avg_brute": lambda: baselines.brute_force(o, t, "avg", 10)}  # noqa: B023
        out += [{"set": data, "run": n, "seconds": timed(r)[0]} for n, r in runs.items()]
    return out


def pruning_height(spark: SparkSession, sf: str) -> list[Row]:
    out = []
    o, t = SETS["part_geo"].load(spark, sf)
    o = o.cache()
    for h in (1, 2, 3):
        m = Metrics()
        s, _ = timed(lambda h=h, m=m: emd_join.emd_topk(o, t, 10, h=h, metrics=m))
        out.append({"height": h, "seconds": s, "exact": m.pairs("exact"), "pairs": m.pairs("bounds")})
    return out


def published_variants(spark: SparkSession, sf: str) -> list[Row]:
    """Agreement of the published forms with the exact answers."""
    out = []
    o, t = SETS["user_activity"].load(spark, sf)
    want = min_join.mindist_topk(o, t, 10)
    r = measures.agreement(min_join.mindist_topk(o, t, 10, list_len="sqrt"), want).first()
    out.append({"variant": "short lists", "precision": r.precision, "kth_error": r.kth_error})
    got = emd_join.progressive(o, t, 10, halved=False).filter("rank > 0").select("rank", "a", "b", "dist")
    r = measures.agreement(got, emd_join.emd_topk(o, t, 10)).first()
    out.append({"variant": "threshold not halved", "precision": r.precision, "kth_error": r.kth_error})
    ids = o.select("obj_id").distinct().limit(60)
    p = ids.select(F.col("obj_id").alias("a")).crossJoin(ids.select(F.col("obj_id").alias("b"))).filter("a < b")
    from .operators.distance import emd_distance

    r = measures.tightness(bounds.l1_full(p, o, t, "published"), emd_distance(p, o, t)).first()
    out.append({"variant": "half L1 over all terms, unscaled", "violations": r.violations, "pairs": r.pairs})
    return out


def extensions_run(spark: SparkSession, sf: str) -> list[Row]:
    o, t = SETS["user_activity"].load(spark, sf)
    g, gt = SETS["part_geo"].load(spark, sf)
    return [
        {"run": "range", "rows": extensions.range_join(o, t, 0.6).count()},
        {"run": "knn", "rows": extensions.knn(g, gt, g.filter("obj_id % 100 = 0"), 5).count()},
        {"run": "keyword", "rows": extensions.keyword_search(*SETS["doc_words"].load(spark, sf), "4:a/an/and/and", 10).count()},
    ]


WORKLOADS: dict[str, Callable[[SparkSession, str], list[Row]]] = {
    f.__name__: f for f in (curation, quality, emd_by_k, emd_by_n, emd_by_terms, emd_by_dimensions, min_by_k, min_by_terms, min_by_n, avg_by_k, avg_eta_by_k, avg_by_n, build_by_n_and_terms, avg_by_terms, brute_comparison, pruning_height, published_variants, extensions_run)
}


def main(args: list[str]) -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    names = [a for a in args if a in WORKLOADS] or list(WORKLOADS)
    sf = next((a for a in args if a not in WORKLOADS), "/root/testdata/sf0.01")
    for name in names:
        for row in WORKLOADS[name](spark, sf):
            print(json.dumps({"workload": name} | row), flush=True)
        spark.catalog.clearCache()


if __name__ == "__main__":
    main(sys.argv[1:])
