"""Modelled cache misses of one round with every vertex active, by paradigm.

Spark has no cache counters, so lines are counted from the edges. Under bins a task owns the
values of one partition, which fit its cache: a line of values is fetched once, the rest is
streamed. Push and pull read values at random: the first touch of a line misses, any later one
with the share of values that the cache cannot hold.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binflow.plans.layout import Graph

LINE, CACHE = 64, 256 << 10


def model_misses(graph: Graph, line: int = LINE, cache: int = CACHE, id_bytes: int = 4, value_bytes: int = 4) -> DataFrame:
    """(paradigm, misses): sc, pc, push and pull."""
    n_lines = F.count_distinct(F.floor(F.col("vid") * value_bytes / line))
    held = min(1.0, cache / max(1, graph.n_vertices * value_bytes))
    sums = graph.part_stats.agg(F.coalesce(F.sum("n_e"), F.lit(0)).alias("e"), F.coalesce(F.sum("n_msg"), F.lit(0)).alias("m"))
    senders = graph.vertices.where("deg > 0").agg(n_lines.alias("src_lines"))
    receivers = graph.edges.select(F.col("dst").alias("vid")).distinct().agg(n_lines.alias("dst_lines"))
    e, m, a, b = (F.col(c) for c in ("e", "m", "src_lines", "dst_lines"))
    one = {
        "sc": a + b + (2 * m * value_bytes + 3 * e * id_bytes) / line,
        "pc": a + b + (2 * m * value_bytes + (m + e) * id_bytes) / line,
        "push": b + F.greatest(e - b, F.lit(0)) * (1 - held) + e * id_bytes / line,
        "pull": a + F.greatest(e - a, F.lit(0)) * (1 - held) + e * id_bytes / line,
    }
    rows = F.array(*(F.struct(F.lit(p).alias("paradigm"), F.round(c.cast("double"), 6).alias("misses")) for p, c in one.items()))
    # three aggregates of one row each
    return sums.crossJoin(senders).crossJoin(receivers).select(F.inline(rows))
