"""Runners of the experiment grids; each returns its grid rows as a DataFrame.

A runner's loop is over cells (programs, graphs, variants), never over data.
"""

from __future__ import annotations

import json
import subprocess
import sys
import time
from collections.abc import Sequence
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binflow.baselines import runs as baselines
from binflow.plans import layout, misses, program
from binflow.plans.engine import Result, run
from binflow.plans.layout import Graph
from binflow.programs import local, runs
from binflow.sources import generators, views
from binflow.storage import table

#: stand-ins of the eight published graphs: four of small diameter, two bipartite ones of links, one of chains in two orders of ids
GRAPHS = ("line_chain", "copurchase", "order_part", "part_supplier", "cust_supplier", "event_chain", "page_links", "host_links")
APPS = ("pagerank", "bfs", "sssp", "cc", "nibble")
#: system -> settings of the engine
SYSTEMS = {"bins": {}, "push": {"paradigm": "push"}, "pull": {"paradigm": "pull"}, "edge": {"paradigm": "edge"}, "blocked": {"paradigm": "blocked"}}
#: variant -> mode; the interleaved one applies to monotone programs
VARIANTS = {"sc": ("sc", 1), "pc": ("pc", 1), "dual": ("auto", 1), "interleaved": ("auto", 2)}
MONOTONE = ("cc", "sssp")


def make(app: str, root: int = 0, eps: float = 1e-9) -> program.VertexProgram:
    return {"bfs": lambda: program.bfs(root), "sssp": lambda: program.sssp(root), "cc": program.connected_components, "pagerank": program.pagerank, "nibble": lambda: program.nibble(root, eps)}[app]()


def load(spark: SparkSession, sf_dir: str, name: str, k: int | None = None) -> Graph:
    """A view, over dense ids and in both directions."""
    edges, _ = layout.relabel(views.symmetrise(views.VIEWS[name](spark, sf_dir)))
    return layout.build(edges, k=k)


def one(graph: Graph, app: str, system: str = "bins", mode: str = "auto", waves: int = 1, rounds: int = 10) -> tuple[Result, float]:
    """A run and its seconds; PageRank and Nibble stop after ``rounds``."""
    began = time.monotonic()
    out = run(graph, make(app), mode=mode, waves=waves, max_rounds=rounds if app in ("pagerank", "nibble") else None, **SYSTEMS[system])
    return out, time.monotonic() - began


def _special(graph: Graph, app: str, rounds: int) -> dict:
    """Baselines that are not a paradigm, as system -> rounds of a run."""
    return {"bfs": {"direction_switching": lambda: len(baselines.bfs_switching(graph, 0)[1])}, "sssp": {"delta_stepping": lambda: baselines.sssp_delta(graph, 0)[1], "topological": lambda: baselines.sssp_topological(graph, 0)[1], "local": lambda: local.sssp_local(graph, 0)[1]}, "pagerank": {"residual": lambda: baselines.pagerank_residual(graph, max_rounds=rounds)[1]}, "cc": {"local": lambda: local.components_local(graph)[1]}}.get(app, {})


def run_time(spark: SparkSession, sf_dir: str, apps: Sequence[str] = APPS, graphs: Sequence[str] = GRAPHS, systems: Sequence[str] | None = None, rounds: int = 10) -> DataFrame:
    """(app, graph, system, seconds, rounds)."""
    rows = []
    for name in graphs:
        g = load(spark, sf_dir, name)
        for app in apps:
            for system in SYSTEMS:
                if systems is None or system in systems:
                    out, seconds = one(g, app, system, waves=2 if system == "bins" and app in MONOTONE else 1, rounds=rounds)
                    rows.append((app, name, system, seconds, out.rounds))
            for system, go in _special(g, app, rounds).items():
                if systems is None or system in systems:
                    began = time.monotonic()
                    n = go()
                    rows.append((app, name, system, time.monotonic() - began, n))
        g.release()
    return spark.createDataFrame(rows, "app string, graph string, system string, seconds double, rounds int")


def locality(spark: SparkSession, sf_dir: str, graphs: Sequence[str] = GRAPHS, k: int | None = None) -> DataFrame:
    """(graph, paradigm, misses): modelled misses of a full round; the cache holds one partition's values."""
    out = None
    for name in graphs:
        g = load(spark, sf_dir, name, k)
        part = misses.model_misses(g, cache=4 * g.q).select(F.lit(name).alias("graph"), "paradigm", "misses")
        out = part if out is None else out.union(part)
    return out


def ordering(spark: SparkSession, sf_dir: str, orders: Sequence[str] = ("user", "time", "hash"), k: int = 16) -> DataFrame:
    """(id_order, edges, crossing, share, msgs): how the order of ids moves crossing edges and messages."""
    n, out = table(spark, sf_dir, "events").count(), None
    for order in orders:
        edges = views.g_event_chain(spark, sf_dir, order)
        msgs = layout.build_bins(edges, layout.width(n, k)).agg(F.count(F.lit(1)).alias("msgs"))
        row = layout.inter_partition_edges(edges, n, k).crossJoin(msgs).select(F.lit(order).alias("id_order"), "*")  # one row each
        out = row if out is None else out.union(row)
    return out


def ablation(spark: SparkSession, sf_dir: str, apps: Sequence[str] = APPS, graphs: Sequence[str] = ("line_chain",), variants: Sequence[str] = tuple(VARIANTS), rounds: int = 10, k: int | None = None) -> DataFrame:
    """(app, graph, variant, seconds, normalised, rounds, model_bytes); normalised by the app's full variant."""
    rows = []
    for name in graphs:
        g = load(spark, sf_dir, name, k)
        for app in apps:
            best, mine = ("interleaved" if app in MONOTONE else "dual"), []
            for variant in variants:
                mode, waves = VARIANTS[variant]
                if waves == 1 or app in MONOTONE:
                    out, seconds = one(g, app, mode=mode, waves=waves, rounds=rounds)
                    mine.append((variant, seconds, out.rounds, float(sum(r["model_bytes"] for r in out.log))))
            base = next((s for v, s, *_ in mine if v == best), None)
            rows += [(app, name, v, s, s / base if base else None, n, b) for v, s, n, b in mine]
        g.release()
    return spark.createDataFrame(rows, "app string, graph string, variant string, seconds double, normalised double, rounds int, model_bytes double")


def per_round(spark: SparkSession, sf_dir: str, apps: Sequence[str] = ("bfs", "cc", "sssp"), graphs: Sequence[str] = ("line_chain",), modes: Sequence[str] = ("sc", "pc", "auto"), rounds: int = 10, k: int | None = None) -> DataFrame:
    """(app, graph, mode, round, frontier, sc_parts, pc_parts, model_bytes, ms)."""
    rows = []
    for name in graphs:
        g = load(spark, sf_dir, name, k)
        for app in apps:
            for mode in modes:
                out, _ = one(g, app, mode=mode, rounds=rounds)
                rows += [(app, name, mode, r["round"], r["frontier"], r["sc_parts"], r["pc_parts"], r["model_bytes"], r["wall_ms"]) for r in out.log]
        g.release()
    return spark.createDataFrame(rows, "app string, graph string, mode string, round int, frontier bigint, sc_parts int, pc_parts int, model_bytes double, ms double")


def mode_mix(spark: SparkSession, sf_dir: str, apps: Sequence[str] = ("pagerank", "bfs", "nibble"), graphs: Sequence[str] = ("line_chain",), rounds: int = 10, k: int | None = None) -> DataFrame:
    """(app, graph, round, sc_parts, pc_parts) of the automatic choice."""
    return per_round(spark, sf_dir, apps, graphs, ("auto",), rounds, k).select("app", "graph", "round", "sc_parts", "pc_parts")


def degree_sweep(spark: SparkSession, scale: int = 10, degrees: Sequence[int] = (1, 2, 4, 8, 16, 32, 64, 128), apps: Sequence[str] = ("pagerank", "bfs"), rounds: int = 10, k: int | None = None) -> DataFrame:
    """(degree, app, edges, r, seconds, growth, rounds, pc_share) over generated graphs of one size; growth: seconds over those of the first degree."""
    rows, base = [], {}
    for degree in degrees:
        g = layout.build(generators.rmat(spark, scale, degree), 1 << scale, k)
        total = g.part_stats.agg(F.sum("n_e"), F.sum("n_msg")).first()
        for app in apps:
            out, seconds = one(g, app, rounds=rounds)
            base.setdefault(app, seconds)
            pc, every = sum(r["pc_parts"] for r in out.log), sum(r["pc_parts"] + r["sc_parts"] for r in out.log)
            rows.append((degree, app, total[0], total[1] / max(1, total[0]), seconds, seconds / base[app], out.rounds, pc / max(1, every)))
        g.release()
    return spark.createDataFrame(rows, "degree int, app string, edges bigint, r double, seconds double, growth double, rounds int, pc_share double")


def shuffle_contrast(graph: Graph, rounds: int = 2) -> DataFrame:
    """(system, shuffle_bytes, seconds) of ``rounds`` full PageRank rounds: messages a bin in both modes against messages an edge."""
    rows = []
    for system, how in [("sc", {"mode": "sc"}), ("pc", {"mode": "pc"}), *((s, SYSTEMS[s]) for s in ("push", "pull", "edge", "blocked"))]:
        out = run(graph, program.pagerank(), max_rounds=rounds, trace=True, **how)
        rows.append((system, sum(r["shuffle_bytes"] for r in out.log), sum(r["wall_ms"] for r in out.log) / 1000))
    return graph.vertices.sparkSession.createDataFrame(rows, "system string, shuffle_bytes bigint, seconds double")


def build_time(spark: SparkSession, sf_dir: str, graphs: Sequence[str] = ("line_chain",), k: int | None = None) -> DataFrame:
    """(graph, edges, k, seconds) of relabelling, binning and dealing a view."""
    rows = []
    for name in graphs:
        began = time.monotonic()
        g = load(spark, sf_dir, name, k)
        edges = sum(s["n_e"] for s in g.stats().values())
        rows.append((name, edges, g.k, time.monotonic() - began))
        g.release()
    return spark.createDataFrame(rows, "graph string, edges bigint, k int, seconds double")


def seed_sweep(spark: SparkSession, sf_dir: str, name: str = "line_chain", eps: Sequence[float] = (1e-9, 1e-4), rounds: int = 20) -> DataFrame:
    """(seed, eps, support): Nibble from the vertices of least and most degree, all seeds of a threshold in one run."""
    g, out = load(spark, sf_dir, name), None
    linked = g.vertices.where("deg > 0")
    seeds = [linked.orderBy(*o).first().vid for o in (("deg", "vid"), (F.col("deg").desc(), "vid"))]
    for e in eps:
        part = runs.nibble(g, sorted(set(seeds)), e, rounds).groupBy("seed").agg(F.count(F.lit(1)).alias("support")).select("seed", F.lit(e).alias("eps"), "support")
        out = part if out is None else out.union(part)
    return out


def scaling(scales: Sequence[int], threads: Sequence[int], degree: int = 16, apps: Sequence[str] = ("pagerank",), rounds: int = 3) -> list[dict]:
    """Seconds, speed-up and growth of each (scale, threads), against the first pair, each in a process of its own.

    Equal scales give strong scaling; scales that grow with the threads give weak scaling.
    """
    rows: list[dict] = []
    for n, scale in zip(threads, scales, strict=True):
        asked = json.dumps({"n": n, "scale": scale, "degree": degree, "apps": list(apps), "rounds": rounds})
        said = subprocess.run([sys.executable, "-c", "from binflow import workloads; workloads.scaling_cell()", asked], capture_output=True, text=True, check=True, cwd=Path(__file__).resolve().parents[1])
        rows += json.loads(said.stdout.strip().splitlines()[-1])
    first = {r["app"]: r["seconds"] for r in reversed(rows)}
    return [r | {"speedup": first[r["app"]] / r["seconds"], "growth": r["seconds"] / first[r["app"]]} for r in rows]


def scaling_cell() -> None:
    """One process of ``scaling``: the second run of each program is timed."""
    asked = json.loads(sys.argv[1])
    n, scale = asked["n"], asked["scale"]
    spark = SparkSession.builder.master(f"local[{n}]").config("spark.sql.shuffle.partitions", 4 * n).config("spark.ui.enabled", "false").getOrCreate()
    g, rows = layout.build(generators.rmat(spark, scale, asked["degree"]), 1 << scale), []
    for app in asked["apps"]:
        one(g, app, rounds=asked["rounds"])
        out, seconds = one(g, app, rounds=asked["rounds"])
        rows.append({"scale": scale, "threads": n, "app": app, "seconds": seconds, "rounds": out.rounds})
    print(json.dumps(rows))
    spark.stop()
