"""The programs as functions of a graph."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from binflow.plans import engine, program
from binflow.plans.engine import Result, run
from binflow.plans.layout import Graph
from binflow.plans.modes import choose
from binflow.storage import cut, drop_cut


def bfs(graph: Graph, root: int, mode: str = "auto", paradigm: str = "bins", max_rounds: int | None = None, waves: int = 1) -> DataFrame:
    """(vid, parent, level) of the vertices that the root reaches; the root is its own parent."""
    out = run(graph, program.bfs(root), mode, paradigm, max_rounds, waves).state
    return out.where("x is not null").select("vid", F.col("x").alias("parent"), F.col("since").alias("level"))


def sssp(graph: Graph, root: int, mode: str = "auto", paradigm: str = "bins", waves: int = 1) -> DataFrame:
    """(vid, dist) of the vertices that the root reaches. ``waves`` > 1 interleaves: fewer rounds, but a shuffle and a barrier for each wave."""
    out = run(graph, program.sssp(root), mode, paradigm, waves=waves).state
    return out.where("x is not null").select("vid", F.col("x").alias("dist"))


def connected_components(graph: Graph, mode: str = "auto", paradigm: str = "bins", waves: int = 1) -> DataFrame:
    """(vid, label = smallest vertex of the component) over edges in both directions."""
    return run(graph, program.connected_components(), mode, paradigm, waves=waves).state.select("vid", F.col("x").alias("label"))


def pagerank(graph: Graph, rounds: int = 10, d: float = 0.85, mode: str = "auto", dangling: str = "lose") -> DataFrame:
    """(vid, rank) after a fixed number of rounds, all vertices active.

    As the frontier never changes, every partition's mode is chosen once. Where all choose
    alike the rounds are one lazy plan of one shuffle each, cut now and then; else each round
    is cut, for it reads its state twice. ``dangling`` lose keeps the mass of vertices without
    out-edges out of the sum, uniform spreads it (one scalar a round).
    """
    n, one = graph.n_vertices, program.pagerank(d)
    stats = graph.stats()
    plan = choose({p: (s["n_v"], s["n_e"], s["n_msg"]) for p, s in stats.items()}, stats, graph.k, mode)
    sc, pc = ([p["part"] for p in plan if p["mode"] == m] for m in ("sc", "pc"))
    mixed = bool(sc and pc)
    sc, pc = (sc, pc) if mixed else (() if sc else None, None if sc else ())
    state = graph.vertices.select("part", "vid", "deg", "opd", F.lit(1.0 / max(1, n)).alias("x"), F.lit(True).alias("active"))
    written = None
    with engine.fixed_dealing(graph.vertices.sparkSession):
        for r in range(rounds):
            total = F.coalesce("m", F.lit(0.0))
            rows = graph.vertices.join(engine.combined(graph, state, one, sc, pc).hint("shuffle_hash"), ["part", "vid"], "left")
            if dangling == "uniform":
                lost = state.agg(F.coalesce(F.sum(F.when(F.col("deg") == 0, F.col("x"))), F.lit(0.0))).first()[0]
                total = total + lost / n
            state = rows.select("part", "vid", "deg", "opd", ((1 - d) / n + d * total).alias("x"), F.lit(True).alias("active"))
            if r + 1 < rounds and (mixed or dangling == "uniform" or (r + 1) % engine.CUT_EVERY == 0):
                state = cut(state)
                drop_cut(written)
                written = state
    return state.select("vid", F.col("x").alias("rank"))


def spmv(graph: Graph, x: DataFrame | None = None) -> DataFrame:
    """(vid, y): y[v] = sum of x[u] w(u, v) over in-edges; ``x(vid, x)`` defaults to ones."""
    state = graph.vertices.withColumn("x", F.lit(1.0)) if x is None else graph.vertices.join(x, "vid", "left").select("part", "vid", "deg", "opd", F.coalesce("x", F.lit(0.0)).alias("x"))
    one = program.spmv()
    messages = engine.scatter_pc(graph, state.withColumn("active", F.lit(True)), one)
    rows = graph.vertices.join(engine.combine(messages, one), ["part", "vid"], "left")
    return rows.select("vid", F.coalesce("m", F.lit(0.0)).alias("y"))


def _send(graph: Graph, frontier: DataFrame, value, keys: list[str], parts: list[int]) -> DataFrame:
    """(keys, part, vid, p): what the frontier sends, summed a target and dealt to its owner. Only bins of the frontier's partitions are read."""
    sent = frontier.select(*keys, F.col("part").alias("src_part"), F.col("vid").alias("src"), value.alias("val"))
    bins = engine.listed(graph.by_source, "src_part", parts, graph.k).select("src_part", "src", "dst_part", "dst")
    rows = bins.join(sent.hint("shuffle_hash"), ["src_part", "src"]).select(*keys, F.col("dst_part").alias("part"), F.explode("dst").alias("vid"), "val")
    return rows.repartitionById(graph.k, "part").groupBy(*keys, "part", "vid").agg(F.sum("val").alias("p"))


def _seeded(graph: Graph, seeds: list[int]) -> DataFrame:
    spark = graph.vertices.sparkSession
    one = spark.createDataFrame([(s, s, 1.0) for s in sorted(set(seeds))], "seed bigint, vid bigint, p double")
    return graph.vertices.join(F.broadcast(one), "vid").select("part", "seed", "vid", "deg", "p")


def nibble(graph: Graph, seeds: list[int], eps: float = 1e-9, max_rounds: int = 20) -> DataFrame:
    """(seed, vid, p): lazy-walk probability around each seed, sparse.

    A vertex is active while p >= eps deg (never without out-edges). Each round it sends
    p / (2 deg) along every edge, keeps p / 2, and stays active by that half alone if it is
    high enough, whether or not anything arrives. State is held for touched vertices only and
    lies with their owners, so a batch of seeds needs no start-up of the size of the graph; a
    round reads the bins of the partitions that have active vertices. Seeds outside the graph
    have no rows.
    """
    high = (F.col("deg") > 0) & (F.col("p") >= eps * F.col("deg"))
    written = None
    with engine.fixed_dealing(graph.vertices.sparkSession):
        state = _seeded(graph, seeds).withColumn("active", F.col("deg") > 0)
        for _ in range(max_rounds):
            parts = [r.part for r in state.where("active").select("part").distinct().collect()]  # k numbers at most
            if not parts:
                break
            arrived = _send(graph, state.where("active"), F.col("p") / (2 * F.col("deg")), ["seed"], parts).withColumnRenamed("p", "got")
            both = state.join(arrived, ["part", "seed", "vid"], "full_outer").withColumnRenamed("deg", "known")
            placed = both.join(graph.vertices.select("part", "vid", "deg"), ["part", "vid"])
            active, p = F.coalesce("active", F.lit(False)), F.coalesce("p", F.lit(0.0))
            kept = F.when(active, p / 2).otherwise(p)
            on = F.col("got").isNotNull() | (active & (kept >= eps * F.col("deg")))
            new = placed.select("part", "seed", "vid", "deg", (kept + F.coalesce("got", F.lit(0.0))).alias("p"), on.alias("on"))
            state = cut(new.select("part", "seed", "vid", "deg", "p", (F.col("on") & high).alias("active")))
            drop_cut(written)
            written = state
    return state.select("seed", "vid", "p")


def sweep_cut(graph: Graph, walk: DataFrame, min_volume: int = 1) -> DataFrame:
    """(seed, k, vid, conductance): prefixes of the walk by p / deg, with each prefix's conductance; the whole graph has none.

    Needs both directions of every edge. Volume is out-degree; an edge leaves the cut when its
    second end joins. The window runs over touched vertices of one seed.
    """
    total = graph.vertices.agg(F.sum("deg")).first()[0]
    ranked = walk.where("p > 0").join(graph.vertices.select("vid", "deg"), "vid").where("deg > 0")
    order = Window.partitionBy("seed").orderBy((F.col("p") / F.col("deg")).desc(), "vid")
    ranked = ranked.withColumn("k", F.row_number().over(order))
    pairs = graph.by_source.select(F.col("src").alias("vid"), F.explode("dst").alias("other")).join(ranked.select("seed", "vid", "k"), "vid")
    back = ranked.select("seed", F.col("vid").alias("other"), F.col("k").alias("k2"))
    inner = pairs.join(back, ["seed", "other"]).where("k2 < k").groupBy("seed", "vid").agg(F.count(F.lit(1)).alias("closing"))
    rows = ranked.join(inner, ["seed", "vid"], "left")
    so_far = order.rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("volume", F.sum("deg").over(so_far)).withColumn("cut", F.sum(F.col("deg") - 2 * F.coalesce("closing", F.lit(0))).over(so_far))
    smaller = F.least("volume", F.lit(total) - F.col("volume"))
    return rows.where((F.col("volume") >= min_volume) & (smaller > 0)).select("seed", F.col("k").cast("int").alias("k"), "vid", (F.col("cut") / smaller).alias("conductance"))


def heat_kernel(graph: Graph, seeds: list[int], t: float = 5.0, terms: int = 10) -> DataFrame:
    """(seed, vid, score): truncated exponential series e^-t sum t^j / j! P^j of the walk from each seed."""
    factor, written = math.exp(-t), None
    with engine.fixed_dealing(graph.vertices.sparkSession):
        at = _seeded(graph, seeds).withColumn("score", F.col("p") * factor)
        for j in range(terms):
            factor *= t / (j + 1)
            going = at.where("p > 0 and deg > 0")
            parts = [r.part for r in going.select("part").distinct().collect()]
            if not parts:
                break
            moved = _send(graph, going, F.col("p") / F.col("deg"), ["seed"], parts).withColumnRenamed("p", "got")
            both = at.select("part", "seed", "vid", "score").join(moved, ["part", "seed", "vid"], "full_outer")
            p = F.coalesce("got", F.lit(0.0))
            new = both.join(graph.vertices.select("part", "vid", "deg"), ["part", "vid"]).select("part", "seed", "vid", "deg", p.alias("p"), (F.coalesce("score", F.lit(0.0)) + p * factor).alias("score"))
            at = cut(new)
            drop_cut(written)
            written = at
    return at.select("seed", "vid", "score")


def validate_bfs(graph: Graph, root: int, tree: DataFrame) -> DataFrame:
    """(check, failures): parent edges exist, levels step by one, no edge spans more than one level, reach is closed."""
    levels = tree.select("vid", "level")
    child = tree.where(F.col("vid") != root)
    edges = graph.edges.select("src", "dst").distinct()
    missing = child.join(edges, (child["parent"] == edges["src"]) & (child["vid"] == edges["dst"]), "left_anti").agg(F.count(F.lit(1)).alias("failures")).select(F.lit("parent edge exists").alias("check"), "failures")
    up = levels.select(F.col("vid").alias("parent"), F.col("level").alias("above"))
    steps = child.join(up, "parent", "left").where(F.col("above").isNull() | (F.col("above") != F.col("level") - 1)).agg(F.count(F.lit(1)).alias("failures")).select(F.lit("level is the parent's plus one"), "failures")
    a, b = levels.select(F.col("vid").alias("src"), F.col("level").alias("ls")), levels.select(F.col("vid").alias("dst"), F.col("level").alias("ld"))
    both = edges.join(a, "src").join(b, "dst", "left")
    spans = both.where(F.col("ld").isNotNull() & (F.col("ld") > F.col("ls") + 1)).agg(F.count(F.lit(1)).alias("failures")).select(F.lit("no edge spans two levels"), "failures")
    open_ = both.where(F.col("ld").isNull()).agg(F.count(F.lit(1)).alias("failures")).select(F.lit("reach is closed"), "failures")
    return missing.union(steps).union(spans).union(open_)


def result_of(graph: Graph, name: str, root: int = 0, **how) -> Result:
    """Run a named program for its log."""
    made = {"bfs": lambda: program.bfs(root), "sssp": lambda: program.sssp(root), "cc": program.connected_components, "pagerank": program.pagerank, "nibble": lambda: program.nibble(root)}[name]()
    return run(graph, made, **how)
