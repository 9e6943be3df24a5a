"""Vertex programs as column expressions."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

Cols = Callable[..., Column]


def _same(x: Column) -> Column:
    return x


def _yes(x: Column) -> Column:
    return F.lit(True)


@dataclass(frozen=True)
class VertexProgram:
    """One program. State columns it may use: x, vid, deg; ``n`` is the number of vertices.

    ``initial``/``starts``: first value and frontier. ``message``: what an active vertex sends.
    ``combine``: min or sum over the (weighed) messages of a vertex. ``reinit``/``stays``: new
    value of a sender and whether it remains active on its own. ``merge``: value after messages;
    ``activates``: whether they make the vertex active. ``finalise``/``keeps``: last change of
    a continuing vertex and whether it stays in the frontier. ``monotone`` programs may repeat
    and interleave messages.
    """

    name: str
    value_type: str
    initial: Callable[[int], Column]
    starts: Callable[[int], Column]
    message: Cols = _same
    combine: str = "min"
    reinit: Cols = _same
    stays: Cols = lambda x: F.lit(False)
    merge: Cols = lambda x, m: F.least(x, m)
    activates: Cols = lambda x, y: y < x
    finalise: Callable[[Column, int], Column] = lambda x, n: x
    keeps: Cols = _yes
    weigh: Cols | None = None
    monotone: bool = False


def bfs(root: int) -> VertexProgram:
    """Parents: the smallest active in-neighbour of the round that reaches a vertex."""
    return VertexProgram("bfs", "bigint", lambda n: F.when(F.col("vid") == root, F.lit(root)).cast("bigint"), lambda n: F.col("vid") == root, message=lambda x: F.col("vid"), merge=lambda x, m: F.coalesce(x, m), activates=lambda x, y: x.isNull() & y.isNotNull())


def sssp(root: int) -> VertexProgram:
    return VertexProgram("sssp", "bigint", lambda n: F.when(F.col("vid") == root, F.lit(0)).cast("bigint"), lambda n: F.col("vid") == root, merge=lambda x, m: F.least(x, m), activates=lambda x, y: x.isNull() | (y < x), weigh=lambda m, w: m + w, monotone=True)


def connected_components() -> VertexProgram:
    """Label propagation; needs both directions of every edge."""
    return VertexProgram("cc", "bigint", lambda n: F.col("vid"), lambda n: F.lit(True), monotone=True)


def pagerank(d: float = 0.85) -> VertexProgram:
    """Topological: all vertices active in every round; mass of vertices without out-edges is lost."""
    return VertexProgram("pagerank", "double", lambda n: F.lit(1.0 / n), lambda n: F.lit(True), message=lambda x: F.when(F.col("deg") > 0, x / F.col("deg")), combine="sum", reinit=lambda x: F.lit(0.0), stays=_yes, merge=lambda x, m: x + m, activates=lambda x, y: F.lit(True), finalise=lambda x, n: (1 - d) / n + d * x)


def spmv() -> VertexProgram:
    """One weighed send and sum."""
    return VertexProgram("spmv", "double", lambda n: F.lit(1.0), lambda n: F.lit(True), combine="sum", reinit=lambda x: F.lit(0.0), merge=lambda x, m: x + m, activates=lambda x, y: F.lit(True), keeps=lambda x: F.lit(False), weigh=lambda m, w: m * w)


def nibble(seed: int, eps: float = 1e-9) -> VertexProgram:
    """Walk probability of one seed with dense state (the sparse form is binflow.programs.nibble)."""
    high = lambda x: (F.col("deg") > 0) & (x >= eps * F.col("deg"))
    return VertexProgram("nibble", "double", lambda n: F.when(F.col("vid") == seed, 1.0).otherwise(0.0), lambda n: (F.col("vid") == seed) & (F.col("deg") > 0), message=lambda x: x / (2 * F.col("deg")), combine="sum", reinit=lambda x: x / 2, stays=lambda x: high(x / 2), merge=lambda x, m: x + m, activates=lambda x, y: F.lit(True), keeps=high)


def python_function(fn: Callable, value_type: str) -> Cols:
    """A program's function from a Python one over pandas Series, for what column expressions cannot say: ``replace(p, message=python_function(f, "double"))``."""
    return F.pandas_udf(fn, value_type)
