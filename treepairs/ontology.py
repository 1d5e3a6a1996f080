"""The tree: nodes with their paths from the root, weights as scaled integers."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .checkpoints import checkpoint
from .functions.columns import cut_step, term_distance_col
from .functions.weights import Rule, exponential
from .schemas import ONTOLOGY

#: Rows of a path table up to which it is broadcast; beyond it joins shuffle.
BROADCAST_ROWS = 2_000_000
ROOT = "root"


def _step(node: Column, level: Column, w: Column, depth: Column) -> Column:
    return F.struct(node.cast("string").alias("node_id"), level.cast("int").alias("level"), w.cast("long").alias("w"), depth.cast("long").alias("depth"))


@dataclass(frozen=True)
class Ontology:
    nodes: DataFrame
    scale: int
    height: int
    #: The smallest scaled weight of any edge, and of the edges at the root.
    least_edge: int
    least_top_edge: int

    # -- construction ---------------------------------------------------------------------------------------------
    @staticmethod
    def from_levels(rows: DataFrame, levels: list[Column], rule: Rule | None = None, labels: list[Column] | None = None) -> Ontology:
        """A tree whose nodes are given by level columns of the rows, outermost first; all terms lie at the last level.

        A node's id is its level and the keys on its path, so equal keys below different parents are different nodes.
        No recursion is needed: every path is a row-wise expression.
        """
        height = len(levels)
        weights, scale = (rule or exponential())(height)
        keyed = rows.select(*[lv.cast("string").alias(f"k{i + 1}") for i, lv in enumerate(levels)], *[c.cast("string").alias(f"l{i + 1}") for i, c in enumerate(labels or [])])
        depth, tables = 0, []
        steps = [_step(F.lit(ROOT), F.lit(0), F.lit(0), F.lit(0))]
        tables.append(rows.sparkSession.range(1).select(F.lit(ROOT).alias("node_id"), F.lit(None).cast("string").alias("parent_id"), F.lit(0).alias("level"), F.lit(0).cast("long").alias("w"), F.lit(ROOT).alias("label"), F.lit(0).cast("long").alias("depth"), F.array(*steps).alias("path")))
        for i in range(1, height + 1):
            depth += weights[i]
            steps.append(_step(node_key([F.col(f"k{j}") for j in range(1, i + 1)]), F.lit(i), F.lit(weights[i]), F.lit(depth)))
            names = [f"k{j}" for j in range(1, i + 1)] + ([f"l{i}"] if labels else [])
            distinct = keyed.select(*names).dropna(subset=[f"k{i}"]).dropDuplicates([f"k{j}" for j in range(1, i + 1)])
            here, above = steps[i], steps[i - 1]
            tables.append(distinct.select(here["node_id"].alias("node_id"), above["node_id"].alias("parent_id"), F.lit(i).alias("level"), F.lit(weights[i]).cast("long").alias("w"), F.col(f"l{i}" if labels else f"k{i}").alias("label"), F.lit(depth).cast("long").alias("depth"), F.array(*steps[: i + 1]).alias("path")))
        nodes = tables[0]
        for t in tables[1:]:
            nodes = nodes.unionByName(t)
        used = [weights[i] for i in range(1, height + 1)] or [1]
        return Ontology(nodes, scale, height, min(used), used[0])

    @staticmethod
    def from_edges(edges: DataFrame, rule: Rule | None = None, weight: str | None = None, scale: int = 1, max_height: int = 64) -> Ontology:
        """A tree from (child, parent) rows; a null parent marks the root. With ``weight`` a column of scaled integer
        weights is used, otherwise the rule by level. One join a level."""
        e = edges.select(F.col("child").cast("string").alias("node_id"), F.col("parent").cast("string").alias("parent_id"), (F.col(weight).cast("long") if weight else F.lit(1).cast("long")).alias("ew"))
        # Levels first, without weights; a cycle or an orphan is never reached.
        front = checkpoint(e.filter("parent_id IS NULL").select("node_id", F.array("node_id").alias("ids"), F.array(F.lit(0).cast("long")).alias("ews")))
        reached, height = [front], 0
        while True:
            front = e.join(front.select(F.col("node_id").alias("p"), "ids", "ews"), F.col("parent_id") == F.col("p")).select("node_id", F.concat("ids", F.array("node_id")).alias("ids"), F.concat("ews", F.array("ew")).alias("ews"))
            front = checkpoint(front)
            if front.isEmpty():
                break
            if height == max_height:
                raise ValueError(f"the tree is deeper than {max_height} levels")
            reached.append(front)
            height += 1
        paths = reached[0]
        for r in reached[1:]:
            paths = paths.unionByName(r)
        if weight:
            stats = e.filter("parent_id IS NOT NULL").agg(F.min("ew")).first()[0] or 1
            top = reached[1].agg(F.min(F.element_at("ews", -1))).first()[0] if height else 1
            ws = F.col("ews")
        else:
            table, scale = (rule or exponential())(height)
            used = [table[i] for i in range(1, height + 1)] or [1]
            stats, top = min(used), used[0]
            ws = F.transform("ids", lambda x, i: F.element_at(F.array(*[F.lit(v).cast("long") for v in [0, *used]]), i + 1))
        steps = F.transform(F.arrays_zip(F.col("ids").alias("i"), ws.alias("w")), lambda s, i: F.struct(s["i"].alias("node_id"), i.cast("int").alias("level"), s["w"].alias("w"), F.aggregate(F.slice(ws, F.lit(1), i + 1), F.lit(0).cast("long"), lambda t, v: t + v).alias("depth")))
        last = F.element_at("path", -1)
        nodes = paths.withColumn("path", steps).select("node_id", F.when(F.size("path") > 1, F.element_at("path", -2)["node_id"]).alias("parent_id"), last["level"].alias("level"), last["w"].alias("w"), F.col("node_id").alias("label"), last["depth"].alias("depth"), "path")
        return Ontology(checkpoint(nodes), scale, height, stats, top)

    @staticmethod
    def from_rows(spark: SparkSession, parents: dict[str, str | None], weights: dict[str, int] | None = None, scale: int = 1, rule: Rule | None = None) -> Ontology:
        """A small tree from a parent map, for fixtures."""
        rows = [(n, p, (weights or {}).get(n, 1)) for n, p in parents.items()]
        edges = spark.createDataFrame(rows, "child string, parent string, w long")
        return Ontology.from_edges(edges, rule=rule, weight="w" if weights else None, scale=scale)

    # -- use ------------------------------------------------------------------------------------------------------
    def size(self) -> int:
        return self.nodes.count()

    def paths(self) -> DataFrame:
        """term_id, path; broadcast only if a count shows that it is small."""
        found = self.nodes.select(F.col("node_id").alias("term_id"), "path")
        return F.broadcast(found) if self.nodes.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else found

    def closure(self) -> DataFrame:
        """node_id, anc_id, anc_level, dist (scaled); each node is its own ancestor at 0."""
        step = self.nodes.select("node_id", "depth", F.explode("path").alias("s"))
        return step.select("node_id", F.col("s.node_id").alias("anc_id"), F.col("s.level").alias("anc_level"), (F.col("depth") - F.col("s.depth")).alias("dist"))

    def cut(self, h: int) -> DataFrame:
        """term_id, kept_id: the term itself, or its ancestor at height ``h``."""
        return self.nodes.select(F.col("node_id").alias("term_id"), cut_step(F.col("path"), h)["node_id"].alias("kept_id"))

    def term_distance(self, pairs: DataFrame, height: int | None = None, x: str = "x", y: str = "y") -> DataFrame:
        """The pairs with ``dist``."""
        p = self.paths()
        both = pairs.join(p.select(F.col("term_id").alias(x), F.col("path").alias("__px")), x).join(p.select(F.col("term_id").alias(y), F.col("path").alias("__py")), y)
        return both.select(*pairs.columns, (term_distance_col(F.col("__px"), F.col("__py"), height).cast("double") / F.lit(float(self.scale))).alias("dist"))

    def validate(self, declared: DataFrame | None = None) -> dict[str, int]:
        """Counts of faults; all zero for a sound tree. ``declared``: the (child, parent) rows it was made from."""
        n = self.nodes
        out = {
            "roots_missing_or_extra": abs(n.filter("parent_id IS NULL").count() - 1),
            "repeated_nodes": n.groupBy("node_id").count().filter("count > 1").count(),
            "bad_weights": n.filter("parent_id IS NOT NULL AND w <= 0").count(),
            "orphans": n.filter("parent_id IS NOT NULL").join(n.select(F.col("node_id").alias("parent_id")), "parent_id", "left_anti").count(),
            # n_i * n_j * 2 * depth must stay below 2**63 for objects of up to 2**20 terms
            "overflow": n.filter(F.col("depth") >= 2 ** (62 - 40)).count(),
        }
        if declared is not None:
            out["unreached"] = declared.select(F.col("child").cast("string").alias("node_id")).join(n.select("node_id"), "node_id", "left_anti").count()
        return out

    def check_metric(self, fraction_mod: int = 1) -> dict[str, int]:
        """Violations of symmetry, identity and the triangle inequality over a deterministic share of the nodes."""
        t = self.nodes.filter(F.pmod(F.xxhash64("node_id"), F.lit(fraction_mod)) == 0).select("node_id", "path")
        a, b, c = (t.select(F.col("node_id").alias(f"n{i}"), F.col("path").alias(f"p{i}")) for i in range(3))
        d = lambda i, j: term_distance_col(F.col(f"p{i}"), F.col(f"p{j}"))
        two, three = a.crossJoin(b), a.crossJoin(b).crossJoin(c)
        return {
            "symmetry": two.filter(d(0, 1) != d(1, 0)).count(),
            "identity": two.filter((d(0, 1) == 0) != (F.col("n0") == F.col("n1"))).count(),
            "triangle": three.filter(d(0, 2) > d(0, 1) + d(1, 2)).count(),
        }


def node_key(keys: list[Column]) -> Column:
    """The id of a node of a levelled tree: its level and the keys on its path."""
    return F.concat(F.lit(f"{len(keys)}:"), F.concat_ws("/", *[k.cast("string") for k in keys]))


def dag_to_tree(edges: DataFrame, policy: str = "shallowest", max_height: int = 64) -> DataFrame:
    """(child, parent) rows of a tree from those of a rooted graph.

    ``shallowest``: each node keeps the parent nearest to the root, the smallest on ties. ``unfold``: each path from the
    root is a node of its own, named by its path; the size can grow with the number of paths.
    """
    e = edges.select(F.col("child").cast("string").alias("child"), F.col("parent").cast("string").alias("parent")).distinct()
    front = e.filter("parent IS NULL").select(F.col("child").alias("node"), F.col("child").alias("name"))
    out = front.select(F.col("name").alias("child"), F.lit(None).cast("string").alias("parent"))
    links, seen = e.filter("parent IS NOT NULL"), front.select("node")
    for height in range(max_height + 1):
        grown = links.join(front.select(F.col("node").alias("parent"), "name"), "parent")
        if policy == "shallowest":
            grown = grown.join(seen.select(F.col("node").alias("child")), "child", "left_anti").groupBy("child").agg(F.min("parent").alias("parent"))
            step = grown.select("child", "parent", F.col("child").alias("node"))
        elif policy == "unfold":
            grown = grown.filter(~F.array_contains(F.split("name", "/"), F.col("child")))
            step = grown.select(F.concat_ws("/", "name", "child").alias("child"), F.col("name").alias("parent"), F.col("child").alias("node"))
        else:
            raise ValueError(policy)
        step = checkpoint(step)
        if step.isEmpty():
            break
        if height == max_height:
            raise ValueError(f"the tree is deeper than {max_height} levels")
        out = out.unionByName(step.select("child", "parent"))
        front = step.select("node", F.col("child").alias("name"))
        seen = seen.unionByName(front.select("node"))
    return out


__all__ = ["BROADCAST_ROWS", "ONTOLOGY", "ROOT", "Ontology", "dag_to_tree", "node_key"]
