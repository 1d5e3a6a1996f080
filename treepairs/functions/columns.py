"""Column expressions over root paths, sparse vectors and lists; all stay in Catalyst."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def shared_depth(path_a: Column, path_b: Column, height: int | None = None) -> Column:
    """Scaled depth of the lowest common ancestor of two paths, or of their cuts."""
    level = F.lit(2**31 - 1 if height is None else height)
    both = F.zip_with(path_a, path_b, lambda x, y: F.when((x["node_id"] == y["node_id"]) & (x["level"] <= level), x["depth"]))
    return F.array_max(both)


def cut_step(path: Column, height: int | None) -> Column:
    """The last step of a path that is at most at the height."""
    return F.element_at(path, -1) if height is None else F.element_at(path, F.least(F.size(path), F.lit(height + 1)))


def term_distance_col(path_a: Column, path_b: Column, height: int | None = None) -> Column:
    """Scaled length of the path between two nodes, each given by its path from the root."""
    return cut_step(path_a, height)["depth"] + cut_step(path_b, height)["depth"] - 2 * shared_depth(path_a, path_b, height)


def ratio(num: Column, den: Column) -> Column:
    return num.cast("double") / den.cast("double")


def sparse_l1(x: Column, nx: Column, y: Column, ny: Column) -> Column:
    """Sum of ``abs(x*ny - y*nx)`` over the keys of two count maps."""
    zipped = F.map_zip_with(x, y, lambda _, p, q: F.abs(F.coalesce(p, F.lit(0)) * ny - F.coalesce(q, F.lit(0)) * nx))
    return F.aggregate(F.map_values(zipped), F.lit(0).cast("long"), lambda s, v: s + v)


def list_length(k: int, how: str = "safe") -> int:
    """Objects that a node keeps. ``safe``: k+1, exact. ``sqrt``: the published length, which can lose pairs."""
    if how == "safe":
        return k + 1
    if how == "sqrt":
        m = 1
        while m * (m - 1) < 2 * k:
            m += 1
        return m
    raise ValueError(how)
