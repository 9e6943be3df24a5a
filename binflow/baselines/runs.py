"""Baselines that are not a paradigm of the engine: direction switching, residual ranks, bucketed paths."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binflow.plans.layout import Graph
from binflow.storage import materialise


def check_edge_limit(n_edges: int, limit: int = 2**31) -> bool:
    """True below the limit; a framework with 32-bit edge indices refuses more."""
    if n_edges >= limit:
        raise OverflowError(f"{n_edges} edges: the limit is {limit}")
    return True


def bfs_switching(graph: Graph, root: int, direction: str = "auto", alpha: float = 14, beta: float = 24) -> tuple[DataFrame, list[str]]:
    """BFS over vertices: push (top-down), bottom_up, or auto switching by frontier density.

    Bottom-up: every unvisited vertex takes its smallest in-neighbour in the frontier. auto
    goes bottom-up when the frontier's out-edges exceed 1/alpha of all edges, and back when the
    frontier is smaller than 1/beta of the vertices. Returns ((vid, parent, level), directions).
    """
    spark = graph.edges.sparkSession
    n_edges = graph.vertices.agg(F.sum("deg")).first()[0] or 0
    visited = spark.createDataFrame([(root, root, 0)], "vid bigint, parent bigint, level int").join(graph.vertices.select("vid"), "vid", "left_semi").persist()
    level, taken, bottom_up = 0, [], direction == "bottom_up"
    while True:
        frontier = visited.where(F.col("level") == level).select(F.col("vid").alias("src"))
        size = frontier.join(graph.vertices, frontier["src"] == graph.vertices["vid"]).agg(F.count(F.lit(1)).alias("v"), F.coalesce(F.sum("deg"), F.lit(0)).alias("e")).first()
        if not size.v:
            return visited, taken
        if direction == "auto":
            bottom_up = size.e > n_edges / alpha if not bottom_up else size.v >= graph.n_vertices / beta
        taken.append("bottom_up" if bottom_up else "push")
        if bottom_up:
            unvisited = graph.vertices.select(F.col("vid").alias("dst")).join(visited.select(F.col("vid").alias("dst")), "dst", "left_anti")
            into = graph.edges.select("src", "dst").join(unvisited, "dst", "left_semi")
            found = into.join(frontier, "src", "left_semi")
        else:
            found = graph.edges.select("src", "dst").join(frontier, "src", "left_semi")
            found = found.join(visited.select(F.col("vid").alias("dst")), "dst", "left_anti")
        new = found.groupBy(F.col("dst").alias("vid")).agg(F.min("src").alias("parent")).withColumn("level", F.lit(level + 1))
        level += 1
        visited = materialise(visited.union(new), "baseline")


def pagerank_residual(graph: Graph, d: float = 0.85, tol: float = 1e-10, max_rounds: int = 200) -> tuple[DataFrame, int]:
    """Ranks by pushing unsent residuals above ``tol``; converges to the topological limit. Returns ((vid, rank), rounds)."""
    n = graph.n_vertices
    state = graph.vertices.select("vid", "deg", F.lit(0.0).alias("rank"), F.lit((1 - d) / n).alias("res")).persist()
    for r in range(1, max_rounds + 1):
        active = state.where(F.col("res") > tol)
        if not active.limit(1).count():
            return state.select("vid", "rank"), r - 1
        sent = active.where("deg > 0").select(F.col("vid").alias("src"), (d * F.col("res") / F.col("deg")).alias("val"))
        got = graph.edges.join(sent, "src").groupBy(F.col("dst").alias("vid")).agg(F.sum("val").alias("got"))
        high = F.col("res") > tol
        new = state.join(got, "vid", "left").select("vid", "deg", (F.col("rank") + F.when(high, F.col("res")).otherwise(0.0)).alias("rank"), (F.when(high, 0.0).otherwise(F.col("res")) + F.coalesce("got", F.lit(0.0))).alias("res"))
        state = materialise(new, "baseline")
    return state.select("vid", "rank"), max_rounds


def sssp_topological(graph: Graph, root: int, max_rounds: int | None = None) -> tuple[DataFrame, int]:
    """Relax all edges every round until nothing changes. Returns ((vid, dist), rounds)."""
    state = graph.vertices.where(F.col("vid") == root).select("vid", F.lit(0).cast("bigint").alias("dist")).persist()
    before, r = (1, 0), 0
    while max_rounds is None or r < max_rounds:
        r += 1
        reached = graph.edges.join(state, graph.edges["src"] == state["vid"]).select(F.col("dst").alias("vid"), (F.col("dist") + F.col("weight")).alias("dist"))
        state = materialise(state.union(reached).groupBy("vid").agg(F.min("dist").alias("dist")), "baseline")
        now = tuple(state.agg(F.count(F.lit(1)), F.sum("dist")).first())
        if now == before:
            break
        before = now
    return state, r


def sssp_delta(graph: Graph, root: int, delta: int | None = None) -> tuple[DataFrame, int]:
    """Delta-stepping: settle bucket after bucket, light edges to a fix-point, then heavy ones once.

    ``delta`` defaults to the mean weight. Returns ((vid, dist), relaxation rounds).
    """
    if delta is None:
        delta = max(1, int(graph.edges.agg(F.avg("weight")).first()[0] or 1))
    light, heavy = graph.edges.where(F.col("weight") <= delta).persist(), graph.edges.where(F.col("weight") > delta).persist()
    state = graph.vertices.where(F.col("vid") == root).select("vid", F.lit(0).cast("bigint").alias("dist"), F.lit(True).alias("fresh")).persist()
    bucket, rounds = 0, 0

    def relax(state: DataFrame, edges: DataFrame, senders: DataFrame) -> DataFrame:
        """``fresh``: not yet sent at this distance."""
        sent = edges.join(senders, edges["src"] == senders["vid"]).select(F.col("dst").alias("vid"), (F.col("dist") + F.col("weight")).alias("new"))
        best = sent.groupBy("vid").agg(F.min("new").alias("new"))
        both = state.join(best, "vid", "full_outer")
        better = F.col("new").isNotNull() & (F.col("dist").isNull() | (F.col("new") < F.col("dist")))
        return both.select("vid", F.when(better, F.col("new")).otherwise(F.col("dist")).alias("dist"), F.when(better, True).otherwise(F.coalesce("fresh", F.lit(False))).alias("fresh"))

    while True:
        inside = F.floor(F.col("dist") / delta) == bucket
        while state.where(inside & F.col("fresh")).limit(1).count():
            rounds += 1
            senders = state.where(inside & F.col("fresh")).select("vid", "dist")
            rest = state.withColumn("fresh", F.col("fresh") & ~inside)
            state = materialise(relax(rest, light, senders), "baseline")
        rounds += 1
        state = materialise(relax(state, heavy, state.where(inside).select("vid", "dist")), "baseline")
        following = state.where(F.col("dist") >= (bucket + 1) * delta).agg(F.min(F.floor(F.col("dist") / delta))).first()[0]
        if following is None:
            return state.select("vid", "dist"), rounds
        bucket = int(following)
