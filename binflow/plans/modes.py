"""The analytical cost of both scatter modes, as columns, and the choice between them.

Source-centric (SC) touches active vertices and their edges: each edge's id is read,
written and read again, each message's value written and read. Partition-centric (PC)
streams all messages of the partition; ids were written once before, so they are only read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ID_BYTES = VALUE_BYTES = 4
BANDWIDTH_RATIO = 2.0


def cost_sc(v_a: Column, e_a: Column, messages: Column, si: int = ID_BYTES, sv: int = VALUE_BYTES, weight_bytes: int = 0) -> Column:
    """Bytes of an SC round: (V_a + E_a) s_i + 2 (messages s_v + E_a s_i); ``weight_bytes`` counts weights like ids."""
    return (v_a + e_a) * si + 2 * (messages * sv + e_a * si) + 3 * weight_bytes * e_a


def cost_pc(n_e: Column, r: Column, k: int, si: int = ID_BYTES, sv: int = VALUE_BYTES, weight_bytes: int = 0) -> Column:
    """Bytes of a PC round: E ((r + 1) s_i + 2 r s_v) + k s_i."""
    return n_e * ((r + 1) * si + 2 * r * sv) + k * si + weight_bytes * n_e


def mode_plan(active: DataFrame, part_stats: DataFrame, k: int, mode: str = "auto", ratio: float = BANDWIDTH_RATIO, exact: bool = False) -> DataFrame:
    """One row for each partition on the scatter list: costs, work and the chosen mode.

    ``active(part, vid, deg, opd)`` are the active vertices. ``exact`` counts the messages of
    SC (sum of out-partition-degrees) instead of estimating them as r E_a.
    """
    work = active.groupBy("part").agg(F.count(F.lit(1)).alias("v_a"), F.sum("deg").alias("e_a"), F.sum("opd").alias("m_a"))
    rows = work.join(F.broadcast(part_stats), "part")  # one row a partition: k rows
    messages = F.col("m_a") if exact else F.col("r") * F.col("e_a")
    rows = rows.withColumn("cost_sc", cost_sc(F.col("v_a"), F.col("e_a"), messages).cast("double"))
    rows = rows.withColumn("cost_pc", cost_pc(F.col("n_e"), F.col("r"), k).cast("double"))
    chosen = F.when(F.col("cost_pc") / ratio <= F.col("cost_sc"), "pc").otherwise("sc") if mode == "auto" else F.lit(mode)
    return rows.withColumn("mode", chosen).select("part", "v_a", "e_a", "m_a", "n_e", "n_msg", "r", "cost_sc", "cost_pc", "mode")


def choose(front: dict[int, tuple[int, int, int]], stats: dict[int, dict], k: int, mode: str = "auto", ratio: float = BANDWIDTH_RATIO, exact: bool = False) -> list[dict]:
    """``mode_plan`` on the driver, from one (v_a, e_a, m_a) for each partition on the scatter list."""
    if mode not in ("auto", "sc", "pc"):
        raise ValueError(f"mode {mode}")
    plan = []
    for part, (v_a, e_a, m_a) in sorted(front.items()):
        s = stats[part]
        sc = float(cost_sc(v_a, e_a, m_a if exact else s["r"] * e_a))
        pc = float(cost_pc(s["n_e"], s["r"], k))
        chosen = mode if mode != "auto" else "pc" if pc / ratio <= sc else "sc"
        plan.append({"part": part, "v_a": v_a, "e_a": e_a, "m_a": m_a, "cost_sc": sc, "cost_pc": pc, "mode": chosen} | {c: s[c] for c in ("n_e", "n_msg", "lo", "hi")})
    return plan
