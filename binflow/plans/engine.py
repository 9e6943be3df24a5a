"""The iteration driver and the paradigms it can run a program under.

A round is one shuffle. Static bins lie with the owners of both ends and never move; the state
lies with the owners of the vertices and is cut with reliable checkpoints, which keep that
dealing. SC joins the active vertices with the bins of the listed partitions and sends values
and id lists; PC sends the values of whole partitions and joins them with the id lists that
the target's owner has. The lists of partitions (one number for each of k partitions) are on
the driver and become predicates on the kept tables, whose blocks outside them are skipped.
"""

from __future__ import annotations

import time
from collections.abc import Iterator, Sequence
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from binflow.plans.layout import Graph, part_of
from binflow.plans.modes import BANDWIDTH_RATIO, ID_BYTES, VALUE_BYTES, choose
from binflow.plans.program import VertexProgram
from binflow.storage import cut, drop_cut, shuffle_bytes

#: rounds of a linear plan after which it is cut
CUT_EVERY = 8
#: partitions whose numbers the driver handles
MOST_PARTITIONS = 200_000
#: vertices whose values a pull round may broadcast (16 bytes each); above, they are joined by a shuffle
BROADCAST_VALUES = 1 << 20
#: ranges that a list of partitions is written as
MOST_RANGES = 64
#: a round writes changed rows only, while they are fewer than this share of all
CHANGED_SHARE = 0.25
AGGREGATES = {"min": F.min, "sum": F.sum}
LOG = "round int, wave int, frontier bigint, e_active bigint, msgs bigint, ids_sent bigint, sc_parts int, pc_parts int, model_bytes double, best_bytes double, work bigint, touched_parts int, touched_bins bigint, shuffle_bytes bigint, wall_ms double"


@dataclass
class Result:
    state: DataFrame
    log: list[dict] = field(default_factory=list)

    @property
    def rounds(self) -> int:
        return len({r["round"] for r in self.log})

    def log_frame(self) -> DataFrame:
        rows = [tuple(r.get(c.split()[0]) for c in LOG.split(", ")) for r in self.log]
        return self.state.sparkSession.createDataFrame(rows, LOG)


def start(graph: Graph, program: VertexProgram) -> DataFrame:
    """Initial state (part, vid, deg, opd, x, active, since)."""
    n = graph.n_vertices
    x = program.initial(n).cast(program.value_type)
    return graph.vertices.select("part", "vid", "deg", "opd", x.alias("x"), F.coalesce(program.starts(n), F.lit(False)).alias("active"), F.when(program.starts(n), 0).cast("int").alias("since"))


@contextmanager
def fixed_dealing(spark: SparkSession) -> Iterator[None]:
    """Plans made inside keep their partitioning: adaptive execution would hide it from the next round."""
    before = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        yield
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", before)


def listed(rows: DataFrame, col: str, parts: Sequence[int] | None, k: int) -> DataFrame:
    """Rows of the partitions ``parts`` (None or all k: every row).

    Ranges come first: kept tables compare them with the bounds of their blocks and skip whole
    blocks. Where the list has more gaps than MOST_RANGES, the smallest gaps are bridged and
    the exact list is tested besides.
    """
    if parts is None or len(parts) >= k:
        return rows
    if not parts:
        return rows.where(F.lit(False))
    parts = sorted(parts)
    gaps = sorted((b - a for a, b in zip(parts, parts[1:], strict=False) if b - a > 1), reverse=True)
    bridged = gaps[MOST_RANGES - 1] if len(gaps) >= MOST_RANGES else 1
    test, low = F.lit(False), parts[0]
    for a, b in zip(parts, [*parts[1:], None], strict=True):
        if b is None or b - a > bridged:
            test = test | F.col(col).between(low, a)
            low = b
    rows = rows.where(test)
    return rows if bridged == 1 else rows.where(F.col(col).isin(*parts))


def reach(plan: list[dict]) -> set[int]:
    """Partitions that the plan's partitions may send to: the static bounds of their bins."""
    out: set[int] = set()
    end = -1
    for lo, hi in sorted((p["lo"], p["hi"]) for p in plan if p["lo"] is not None):
        out.update(range(max(lo, end + 1), hi + 1))
        end = max(end, hi)
    return out


class State:
    """Values of all vertices: ``base``, and ``delta`` with the rows that have changed since, both dealt by partition."""

    def __init__(self, graph: Graph, base: DataFrame):
        self.graph, self.base, self.delta = graph, base, None
        self.delta_parts: set[int] = set()

    def rows(self, parts: Sequence[int] | None = None) -> DataFrame:
        """Current (part, vid, deg, opd, x, active, since, fresh) of the listed partitions; fresh: from ``delta``."""
        base = listed(self.base, "part", parts, self.graph.k)
        if self.delta is None:
            return base.withColumn("fresh", F.lit(False))
        new = listed(self.delta, "part", parts, self.graph.k).select("part", "vid", F.col("x").alias("x1"), F.col("active").alias("active1"), F.col("since").alias("since1"), F.lit(True).alias("fresh"))
        both = base.join(new.hint("shuffle_hash"), ["part", "vid"], "left")
        newer = F.col("fresh").isNotNull()
        return both.select("part", "vid", "deg", "opd", *(F.when(newer, F.col(f"{c}1")).otherwise(F.col(c)).alias(c) for c in ("x", "active", "since")), newer.alias("fresh"))

    def replace_base(self, rows: DataFrame) -> None:
        """``rows`` are kept in memory besides, for their blocks can be skipped there."""
        old, self.base, self.delta, self.delta_parts = (self.base, self.delta), rows.persist(), None, set()
        old[0].unpersist()
        for df in old:
            drop_cut(df)

    def replace_delta(self, rows: DataFrame, parts: set[int]) -> None:
        old, self.delta, self.delta_parts = self.delta, rows, parts
        drop_cut(old)


def scatter_sc(graph: Graph, active: DataFrame, program: VertexProgram, parts: Sequence[int] | None = None) -> DataFrame:
    """Messages with their id lists, from the active vertices only; dealt to the target's owner. Only bins of the listed partitions are read."""
    sent = active.select(F.col("part").alias("src_part"), F.col("vid").alias("src"), program.message(F.col("x")).alias("val")).where("val is not null")
    rows = listed(graph.by_source, "src_part", parts, graph.k).join(sent.hint("shuffle_hash"), ["src_part", "src"])
    return rows.select("dst_part", "val", "dst", *["wt"] * bool(program.weigh)).repartitionById(graph.k, "dst_part")


def scatter_pc(graph: Graph, state: DataFrame, program: VertexProgram, parts: Sequence[int] | None = None, targets: Sequence[int] | None = None) -> DataFrame:
    """Messages of whole partitions: values travel, the id lists wait with the target's owner.

    An inactive vertex sends no value unless the program may repeat messages.
    """
    value = program.message(F.col("x"))
    value = value if program.monotone else F.when(F.col("active"), value)
    sent = state.select(F.col("part").alias("src_part"), F.col("vid").alias("src"), value.alias("val"))
    slim = listed(graph.by_source, "src_part", parts, graph.k).select("src_part", "src", "dst_part", "chunk")
    moved = slim.join(sent.hint("shuffle_hash"), ["src_part", "src"]).where("val is not null").repartitionById(graph.k, "dst_part")
    waiting = listed(listed(graph.by_target, "dst_part", targets, graph.k), "src_part", parts, graph.k)
    lists = waiting.select("dst_part", "src_part", "src", "chunk", "dst", *["wt"] * bool(program.weigh))
    return lists.join(moved, ["dst_part", "src_part", "src", "chunk"]).select("dst_part", "val", "dst", *["wt"] * bool(program.weigh))


def combine(messages: DataFrame, program: VertexProgram) -> DataFrame:
    """(part, vid, m): messages unpacked, weighed and combined where they lie."""
    if program.weigh:
        one = messages.select("dst_part", "val", F.inline(F.arrays_zip("dst", "wt"))).select("dst_part", F.col("dst").alias("vid"), program.weigh(F.col("val"), F.col("wt")).alias("val"))
    else:
        one = messages.select("dst_part", "val", F.explode("dst").alias("vid"))
    return one.groupBy("dst_part", "vid").agg(AGGREGATES[program.combine]("val").alias("m")).withColumnRenamed("dst_part", "part")


def combined(graph: Graph, state: DataFrame, program: VertexProgram, sc: Sequence[int] | None, pc: Sequence[int] | None, targets: Sequence[int] | None = None) -> DataFrame:
    """What arrives (part, vid, m) when the partitions ``sc`` and ``pc`` scatter in those modes; None lists none, () stands for all."""
    found = []
    if sc is not None:
        mine = listed(state, "part", sc or None, graph.k).where("active")
        found.append(combine(scatter_sc(graph, mine, program, sc or None), program))
    if pc is not None:
        found.append(combine(scatter_pc(graph, listed(state, "part", pc or None, graph.k), program, pc or None, targets), program))
    if len(found) == 1:
        return found[0]
    both = found[0].join(found[1].withColumnRenamed("m", "m2").hint("shuffle_hash"), ["part", "vid"], "full_outer")
    m = F.least("m", "m2") if program.combine == "min" else F.coalesce("m", F.lit(0)) + F.coalesce("m2", F.lit(0))
    return both.select("part", "vid", m.alias("m"))


def gather(graph: Graph, state: DataFrame, arrived: DataFrame, program: VertexProgram, round_: int, sends: Column) -> DataFrame:
    """Next state, with ``touched``: re-initialise senders, merge what arrived, finalise continuing vertices.

    ``sends`` marks the active vertices that scattered; active ones that did not stay so.
    """
    x, n, got = F.col("x"), graph.n_vertices, F.col("m").isNotNull()
    before = F.when(sends, program.reinit(x)).otherwise(x).cast(program.value_type)
    after = F.when(got, program.merge(before, F.col("m").cast(program.value_type))).otherwise(before)
    hit = got & F.coalesce(program.activates(before, after), F.lit(False))
    stay = F.coalesce(F.when(sends, program.stays(x)).otherwise(F.col("active")), F.lit(False))
    same = ("part", "vid", "deg", "opd")
    rows = state.join(arrived.hint("shuffle_hash"), ["part", "vid"], "left").select(*same, "active", "fresh", "since", after.alias("x"), hit.alias("hit"), (stay | hit).alias("goes"))
    final = F.when(F.col("goes"), program.finalise(F.col("x"), n)).otherwise(F.col("x")).cast(program.value_type)
    keep = F.col("goes") & F.coalesce(program.keeps(final), F.lit(False))
    since = F.when(F.col("hit"), F.lit(round_)).otherwise(F.col("since")).cast("int")
    return rows.select(*same, final.alias("x"), keep.alias("active"), since.alias("since"), (F.col("hit") | F.col("active") | F.col("fresh")).alias("touched"))


def vertex_messages(graph: Graph, state: DataFrame, program: VertexProgram, paradigm: str, blocks: int = 16) -> DataFrame:
    """(part, vid, m) under the paradigms that the engine is compared with.

    push: active vertices send one message an edge, and every message travels on its own.
    pull: vertices read all their in-edges, which lie with them; what travels are the values of
    all vertices, to everyone if they are few (checked), else to each edge. edge: all edges are
    streamed where their sources lie, and one update an edge is written to its target's
    partition. blocked: as edge, but updates of a block of targets are first combined where
    they are made, and blocks have no owner: the result is dealt by vertex.
    """
    value = program.message(F.col("x"))
    active_value = F.when(F.col("active"), value)
    agg = AGGREGATES[program.combine]
    weigh = program.weigh or (lambda m, w: m)
    part = part_of("vid", graph.q).alias("part")
    if paradigm == "pull":
        sent = state.select(F.col("vid").alias("src"), (value if program.monotone else active_value).alias("val")).where("val is not null")
        small = graph.n_vertices <= BROADCAST_VALUES
        rows = graph.in_edges().join(F.broadcast(sent) if small else sent, "src").select(F.col("dst").alias("vid"), weigh(F.col("val"), F.col("weight")).alias("val"))
        return rows.groupBy("vid").agg(agg("val").alias("m")).select(part, "vid", "m")
    if paradigm not in ("push", "edge", "blocked"):
        raise ValueError(paradigm)
    sent = state.where("active") if paradigm == "push" else state
    sent = sent.select(F.col("part").alias("src_part"), F.col("vid").alias("src"), active_value.alias("val"))
    rows = graph.edges_by_source().join(sent.hint("shuffle_hash"), ["src_part", "src"]).select(F.col("dst").alias("vid"), weigh(F.col("val"), F.col("weight")).alias("val"))
    if paradigm == "edge":
        rows = rows.select("vid", "val", part).repartitionById(graph.k, "part").where("val is not null")
        return rows.groupBy("part", "vid").agg(agg("val").alias("m"))
    rows = rows.where("val is not null")
    if paradigm == "push":
        return rows.repartition(graph.k, "vid").groupBy("vid").agg(agg("val").alias("m")).select(part, "vid", "m")
    block = part_of("vid", max(1, -(-graph.n_vertices // blocks))).alias("block")
    return rows.select(block, "vid", "val").groupBy("block", "vid").agg(agg("val").alias("m")).select(part, "vid", "m")


def _front(rows: DataFrame) -> tuple[dict[int, tuple[int, int, int]], int]:
    """(v_a, e_a, m_a) of every partition with active vertices, and the number of rows: k rows come to the driver."""
    on = F.col("active")
    sums = rows.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(on, 1)).alias("v"), F.coalesce(F.sum(F.when(on, F.col("deg"))), F.lit(0)).alias("e"), F.coalesce(F.sum(F.when(on, F.col("opd"))), F.lit(0)).alias("m")).collect()
    return {r["part"]: (r["v"], r["e"], r["m"]) for r in sums if r["v"]}, sum(r["n"] for r in sums)


def _touched(graph: Graph, state: State, plan: list[dict], program: VertexProgram) -> dict:
    """Partitions and bins that the round writes to: those of SC's active vertices, all bins of PC's partitions."""
    slim = graph.by_source.select("src_part", "src", "dst_part")
    pairs = None
    for mode in ("sc", "pc"):
        parts = [p["part"] for p in plan if p["mode"] == mode]
        if parts:
            rows = listed(slim, "src_part", parts, graph.k)
            if mode == "sc" or not program.monotone:
                rows = rows.join(state.rows(parts).where("active").select(F.col("part").alias("src_part"), F.col("vid").alias("src")), ["src_part", "src"], "left_semi")
            rows = rows.select("src_part", "dst_part").distinct()
            pairs = rows if pairs is None else pairs.union(rows)
    row = pairs.agg(F.count(F.lit(1)).alias("bins"), F.count_distinct("dst_part").alias("parts")).first()
    return {"touched_parts": row.parts, "touched_bins": row.bins}


def _slices(parts: list[int], n: int) -> list[list[int]]:
    """The list in at most ``n`` ordered, nearly equal slices."""
    n = max(1, min(n, len(parts)))
    return [parts[i * len(parts) // n : (i + 1) * len(parts) // n] for i in range(n)]


def run(graph: Graph, program: VertexProgram, mode: str = "auto", paradigm: str = "bins", max_rounds: int | None = None, waves: int = 1, ratio: float = BANDWIDTH_RATIO, exact: bool = False, trace: bool = False) -> Result:
    """Run a program until no vertex is active or ``max_rounds`` are over.

    ``paradigm`` bins: messages a bin, each partition choosing its mode (``mode`` auto, sc or
    pc); the others see ``vertex_messages``. ``waves`` > 1 interleaves scatter and gather: the
    partitions on the round's scatter list go in that many ordered slices, and each slice sees
    what earlier ones sent. Only monotone programs may interleave.

    A sparse round reads the partitions on its lists and writes the rows that changed; a dense
    one, or one after which too many rows have changed, writes all rows. Both are cut with a
    reliable checkpoint, so a lost executor costs the current round at most. One row a
    partition comes to the driver after each wave: the next scatter list with its work.

    ``trace`` adds to the log what costs extra jobs: partitions and bins touched, bytes shuffled.
    The state of the result stays on file for as long as the caller may read it.
    """
    if waves > 1 and not program.monotone:
        raise ValueError(f"{program.name} is not monotone: its messages may not be interleaved")
    if graph.k > MOST_PARTITIONS:
        raise ValueError(f"{graph.k} partitions: their numbers would be too many for the driver")
    spark, stats, log = graph.vertices.sparkSession, graph.stats(), []
    with fixed_dealing(spark):
        first = start(graph, program)
        state = State(graph, first)
        front, _ = _front(first)
        round_, everywhere = 0, graph.n_vertices
        while front and (max_rounds is None or round_ < max_rounds):
            round_ += 1
            for wave, mine in enumerate(_slices(sorted(front), waves)):
                clock, shuffled = time.monotonic(), shuffle_bytes(spark) if trace else 0
                plan = choose({p: front[p] for p in mine}, stats, graph.k, mode, ratio, exact)
                sc, pc = ([p["part"] for p in plan if p["mode"] == m] or None for m in ("sc", "pc"))
                targets = reach(plan)
                row = _log_row(plan, ratio) | (_touched(graph, state, plan, program) if trace else {})
                near = targets | set(mine) | state.delta_parts
                dense = paradigm != "bins" or row["frontier"] > CHANGED_SHARE / 2 * everywhere
                whole = state.rows(None if dense else sorted(near))
                if paradigm == "bins":
                    arrived = combined(graph, whole, program, sc, pc, sorted(targets))
                else:
                    arrived = vertex_messages(graph, whole, program, paradigm)
                    dealt = part_of("vid", graph.q)
                    if paradigm != "edge":
                        arrived = arrived.withColumn("part", dealt).repartitionById(graph.k, "part")
                scatters = F.col("active") if len(mine) == len(front) else F.col("active") & F.col("part").isin(*mine)
                new = gather(graph, whole, arrived, program, round_, scatters)
                if dense:
                    state.replace_base(cut(new.drop("touched")))
                    front, _ = _front(state.base)
                else:
                    delta = cut(new.where("touched").drop("touched"))
                    now, size = _front(delta)
                    state.replace_delta(delta, near)
                    front = {p: f for p, f in front.items() if p not in near} | now
                    if size > CHANGED_SHARE * everywhere:
                        state.replace_base(cut(state.rows().drop("fresh")))
                log.append({"round": round_, "wave": wave} | row | {"shuffle_bytes": shuffle_bytes(spark) - shuffled if trace else None, "wall_ms": (time.monotonic() - clock) * 1000})
        return Result(state.rows().drop("fresh"), log)


def _log_row(plan: list[dict], ratio: float) -> dict:
    """Work of a round as the modes make it: messages written, ids read, modelled bytes."""
    is_sc = lambda p: p["mode"] == "sc"
    msgs = sum(p["m_a"] if is_sc(p) else p["n_msg"] for p in plan)
    ids = sum(p["e_a"] if is_sc(p) else p["n_e"] for p in plan)
    return {
        "frontier": sum(p["v_a"] for p in plan),
        "e_active": sum(p["e_a"] for p in plan),
        "msgs": msgs,
        "ids_sent": sum(p["e_a"] for p in plan if is_sc(p)),
        "sc_parts": sum(map(is_sc, plan)),
        "pc_parts": sum(not is_sc(p) for p in plan),
        "model_bytes": float(sum(p["cost_sc"] if is_sc(p) else p["cost_pc"] / ratio for p in plan)),
        "best_bytes": float(sum(min(p["cost_sc"], p["cost_pc"] / ratio) for p in plan)),
        "work": msgs + ids,
    }


def check_work_bound(log: list[dict], k: int, ratio: float = BANDWIDTH_RATIO, si: int = ID_BYTES, sv: int = VALUE_BYTES) -> float:
    """Largest ratio of a round's modelled bytes to those that its active vertices and edges alone would need.

    A partition goes to PC only if that costs at most ``ratio`` times its SC bytes, and SC
    bytes are at most 4 ids and 2 values an active edge or vertex: so the largest ratio of work
    to active work is bounded by a constant, whatever the graph. More is an error.
    """
    worst = 0.0
    for r in log:
        active = (r["frontier"] + r["e_active"]) * si
        spent = r["model_bytes"] * (ratio if r["pc_parts"] else 1)
        worst = max(worst, spent / max(1, active))
    limit = ratio * (3 * si + 2 * sv) / si
    if worst > limit:
        raise AssertionError(f"a round's work is {worst:.2f} times its active edges' and vertices'; the bound is {limit}")
    return worst
