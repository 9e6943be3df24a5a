"""Utilities on edge tables ``(src, dst, weight)`` and on the programs' results."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from binflow.storage import forget, materialise


def reverse(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")


def drop_self_loops(edges: DataFrame) -> DataFrame:
    return edges.where("src <> dst")


def dedup_edges(edges: DataFrame, how: str = "min") -> DataFrame:
    """One edge for each pair of ends; ``how`` min, max or sum of the weights."""
    return edges.groupBy("src", "dst").agg({"min": F.min, "max": F.max, "sum": F.sum}[how]("weight").alias("weight"))


def induced_subgraph(edges: DataFrame, members: DataFrame) -> DataFrame:
    """Edges with both ends in ``members(vid)``."""
    inside = edges.join(members.select(F.col("vid").alias("src")), "src", "left_semi")
    return inside.join(members.select(F.col("vid").alias("dst")), "dst", "left_semi").select(edges.columns)


def component_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("label").agg(F.count(F.lit(1)).alias("n"))


def levels_histogram(tree: DataFrame) -> DataFrame:
    """(level, n); the largest level is the root's eccentricity, a lower bound of the diameter."""
    return tree.groupBy("level").agg(F.count(F.lit(1)).alias("n"))


def dangling(vertices: DataFrame) -> DataFrame:
    """Vertices without out-edges."""
    return vertices.where("deg = 0").select("vid")


def k_hop(edges: DataFrame, seeds: DataFrame, k: int) -> DataFrame:
    """(vid, hops): vertices within ``k`` edges of the seeds, with the fewest edges."""
    out = seeds.select("vid", F.lit(0).alias("hops")).distinct()
    for h in range(1, k + 1):
        last = out.where(F.col("hops") == h - 1).select(F.col("vid").alias("src"))
        reached = edges.join(last, "src", "left_semi").select(F.col("dst").alias("vid"), F.lit(h).alias("hops"))
        out = materialise(out.union(reached).groupBy("vid").agg(F.min("hops").alias("hops")), "hops")
    return out


def triangles(edges: DataFrame) -> DataFrame:
    """(triangles): triples of mutually linked vertices, direction aside.

    Every edge points from its end of lower degree to the other, so a vertex has at most
    sqrt(2 E) successors whatever its degree: hubs make no quadratic group.
    """
    pairs = edges.where("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    degree = pairs.select(F.explode(F.array("a", "b")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("d"))
    sized = pairs.join(degree.select(F.col("v").alias("a"), F.col("d").alias("da")), "a").join(degree.select(F.col("v").alias("b"), F.col("d").alias("db")), "b")
    swap = (F.col("da") > F.col("db")) | ((F.col("da") == F.col("db")) & (F.col("a") > F.col("b")))
    arcs = sized.select(F.when(swap, F.col("b")).otherwise(F.col("a")).alias("low"), F.when(swap, F.col("a")).otherwise(F.col("b")).alias("high"))
    wedges = arcs.join(arcs.select("low", F.col("high").alias("other")), "low").where("high < other")
    closed = wedges.join(pairs, (F.col("high") == F.col("a")) & (F.col("other") == F.col("b")), "left_semi")
    return closed.agg(F.count(F.lit(1)).alias("triangles"))


def conductance(edges: DataFrame, inside: Column | None = None, members: DataFrame | None = None) -> DataFrame:
    """(cut, volume, conductance) of a vertex set, given by a test of column ``vid`` or as a table."""
    if members is None:
        ids = edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()
        members = ids.where(inside)
    a = members.select(F.col("vid").alias("src"), F.lit(1).alias("s"))
    b = members.select(F.col("vid").alias("dst"), F.lit(1).alias("d"))
    marked = edges.join(a, "src", "left").join(b, "dst", "left")
    from_in, to_in = F.col("s").isNotNull(), F.col("d").isNotNull()
    sums = marked.agg(F.coalesce(F.sum((from_in & ~to_in).cast("bigint")), F.lit(0)).alias("cut"), F.coalesce(F.sum(from_in.cast("bigint")), F.lit(0)).alias("volume"), F.count(F.lit(1)).alias("total"))
    smaller = F.least("volume", F.col("total") - F.col("volume"))
    return sums.select("cut", "volume", F.round(F.when(smaller > 0, F.col("cut") / smaller), 9).alias("conductance"))


def quantiles(rows: DataFrame, col: str, shares: list[float], exact: bool = False) -> DataFrame:
    """(share, value); sketches unless ``exact``."""
    at = F.array(*map(F.lit, shares))
    found = F.percentile(col, at) if exact else F.percentile_approx(col, at)
    return rows.agg(found.alias("v")).select(F.inline(F.arrays_zip(at.alias("share"), F.col("v").alias("value")))).toDF("share", "value")


def approx_degrees(edges: DataFrame, rsd: float = 0.05) -> DataFrame:
    """(vid, n): about how many different targets a vertex has."""
    return edges.groupBy(F.col("src").alias("vid")).agg(F.approx_count_distinct("dst", rsd).alias("n"))


def pivot_grid(rows: DataFrame, row: str, col: str, val: str, names: list[str]) -> DataFrame:
    """One column for each of ``names`` (given, so that no extra job looks for them)."""
    return rows.groupBy(row).pivot(col, names).agg(F.first(val))


def unpivot_grid(grid: DataFrame, row: str, col: str, val: str) -> DataFrame:
    return grid.unpivot(row, [c for c in grid.columns if c != row], col, val)


def alternating_stars(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(vid, label = smallest vertex of its component) over any ids, both directions implied.

    Alternates two steps until nothing changes: larger neighbours go to the smallest one of a
    vertex, then smaller neighbours with the vertex itself do. Rounds grow with the logarithm of
    the component's size. A vertex's neighbours are never gathered: a step is a minimum and a join.
    """
    links = materialise(edges.where("src <> dst").select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct(), "links")
    before = None
    for _ in range(max_rounds):
        both = links.union(links.select("b", "a"))
        least = both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("m", "a"))
        large = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        small_min = large.groupBy("a").agg(F.min("b").alias("m"))
        moved = large.join(small_min, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        fresh = materialise(moved.union(small_min.select("a", F.col("m").alias("b"))).distinct(), "links")
        now = tuple(fresh.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        forget(links)
        links = fresh
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = links.select(F.col("b").alias("vid")).distinct().select("vid", F.col("vid").alias("label"))
    alone = edges.where("src = dst").select(F.col("src").alias("vid")).distinct()
    found = links.select(F.col("a").alias("vid"), F.col("b").alias("label")).union(roots)
    return found.union(alone.join(found, "vid", "left_anti").select("vid", F.col("vid").alias("label")))
