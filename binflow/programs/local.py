"""Shortest paths and components that settle each partition before anything travels.

A round runs every partition with news to its own fix-point (over edges that stay inside), then
sends along crossing edges only. Rounds follow the number of partition borders on the longest
shortest path, not its number of edges.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binflow.plans.engine import Result
from binflow.plans.layout import Graph
from binflow.storage import forget, materialise, ship_package

_FAR = np.int64(1) << 62


def settle(x: np.ndarray, active: np.ndarray, src: np.ndarray, dst: np.ndarray, weight: np.ndarray, most: int) -> np.ndarray:
    """Lower ``x`` along edges of local indices until nothing changes (or ``most`` steps); marks what still has to be sent.

    Only edges of vertices that changed in the step before are touched.
    """
    order = np.argsort(src, kind="stable")
    dst, weight = dst[order], weight[order]
    first = np.searchsorted(src[order], np.arange(len(x) + 1))
    news, changed = np.flatnonzero(active & (x < _FAR)), active.copy()
    for _ in range(most):
        n = first[news + 1] - first[news]
        if not n.sum():
            break
        at = np.repeat(first[news] - np.cumsum(n) + n, n) + np.arange(int(n.sum()))
        before = x.copy()
        np.minimum.at(x, dst[at], np.repeat(x[news], n) + weight[at])
        news = np.flatnonzero(x < before)
        changed[news] = True
    return changed


def _settler(weighted: bool, most: int):
    def run(state: pd.DataFrame, inner: pd.DataFrame) -> pd.DataFrame:
        state = state.sort_values("vid", ignore_index=True)
        vid, x = state["vid"].to_numpy(), state["x"].fillna(int(_FAR)).to_numpy(np.int64).copy()
        active = state["active"].to_numpy(bool)
        if len(inner) and active.any():
            n = inner["dst"].map(len).to_numpy()
            src = np.searchsorted(vid, np.repeat(inner["src"].to_numpy(), n))
            dst = np.searchsorted(vid, np.concatenate(inner["dst"].to_list()))
            weight = np.concatenate(inner["wt"].to_list()) if weighted else np.zeros(len(dst), np.int64)
            active = settle(x, active, src, dst, weight.astype(np.int64), most)
        far = x >= _FAR
        return pd.DataFrame({"part": state["part"], "vid": vid, "x": pd.array(np.where(far, 0, x), "Int64").copy(), "active": active & ~far}).assign(x=lambda d: d["x"].mask(far))

    return run


def run_local(graph: Graph, start: DataFrame, weighted: bool, most: int = 1 << 30) -> Result:
    """Minimum propagation from ``start(part, vid, x, active)``; ``most`` bounds the inner steps of a round.

    A partition's state and inner edges are one group of a Python task: k must be chosen so that
    they fit (``layout.choose_k`` with the bytes of a vertex and its edges).
    """
    ship_package(graph.edges.sparkSession)
    inner = graph.by_source.where("src_part = dst_part").select(F.col("src_part").alias("part"), "src", "dst", "wt")
    crossing = graph.by_source.where("src_part <> dst_part").select("dst_part", "src", "dst", "wt")
    state, log, written = start, [], None
    while True:
        size = state.where("active").agg(F.count(F.lit(1)).alias("n")).first().n
        if not size:
            return Result(state, log)
        groups = state.groupBy("part").cogroup(inner.groupBy("part"))
        settled = materialise(groups.applyInPandas(_settler(weighted, most), "part int, vid bigint, x bigint, active boolean"), "settled")
        sent = settled.where("active").select(F.col("vid").alias("src"), F.col("x").alias("val"))
        out = crossing.join(sent, "src").select(F.col("dst_part").alias("part"), "val", F.inline(F.arrays_zip("dst", "wt")))
        arrived = out.groupBy("part", F.col("dst").alias("vid")).agg(F.min(F.col("val") + F.col("wt") if weighted else F.col("val")).alias("m"))
        better = F.col("m").isNotNull() & (F.col("x").isNull() | (F.col("m") < F.col("x")))
        # a partition cut off by ``most`` goes on from what changed last
        again = F.col("active") if most < 1 << 30 else F.lit(False)
        rows = settled.join(arrived, ["part", "vid"], "left")
        lower = F.when(better, F.col("m")).otherwise(F.col("x"))
        if most < 1 << 30:
            rows = rows.join(state.select("vid", F.col("x").alias("was")), "vid", "left")
            again = again & (F.col("was").isNull() | (F.col("x") < F.col("was")))
        fresh = materialise(rows.select("part", "vid", lower.alias("x"), (better | again).alias("active")), "state")
        forget(written)
        forget(settled)
        state, written = fresh, fresh
        log.append({"round": len(log) + 1, "frontier": size})


def sssp_local(graph: Graph, root: int, most: int = 1 << 30) -> tuple[DataFrame, int]:
    """((vid, dist), rounds) with partitions settled locally; weights are whole and not negative."""
    start = graph.vertices.select("part", "vid", F.when(F.col("vid") == root, F.lit(0)).cast("bigint").alias("x"), (F.col("vid") == root).alias("active"))
    out = run_local(graph, start, True, most)
    return out.state.where("x is not null").select("vid", F.col("x").alias("dist")), len(out.log)


def components_local(graph: Graph, most: int = 1 << 30) -> tuple[DataFrame, int]:
    """((vid, label), rounds) over edges in both directions."""
    start = graph.vertices.select("part", "vid", F.col("vid").alias("x"), F.lit(True).alias("active"))
    out = run_local(graph, start, False, most)
    return out.state.select("vid", F.col("x").alias("label")), len(out.log)
