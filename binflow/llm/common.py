"""Pieces that several corpus operators share: the tokenizer broadcast, Arrow helpers, connected components."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binflow.llm.bpe import BytePairModel
from binflow.storage import forget, materialise, ship_package

#: edges that one task solves alone (16 bytes each); more are contracted over the cluster
ONE_TASK_EDGES = 250_000
_MODELS: dict[str, BytePairModel] = {}
_WORKER: dict = {}


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def share_model(spark: SparkSession, path: str) -> Broadcast:
    """Broadcast a tokenizer. Its size is that of the vocabulary (4 MB), whatever the data."""
    ship_package(spark)
    if path not in _MODELS:
        _MODELS[path] = BytePairModel(path)
    return spark.sparkContext.broadcast(_MODELS[path])


def once_per_worker(key, make: Callable):
    """Keep an object between the tasks that one Python worker runs."""
    if key not in _WORKER:
        _WORKER.clear()
        _WORKER[key] = make()
    return _WORKER[key]


def slices(batch: pa.RecordBatch, column: str, most_bytes: int = 2_000_000) -> Iterator[pa.RecordBatch]:
    """Parts of a batch whose texts hold about ``most_bytes`` at most, one row at least."""
    import pyarrow.compute as pc

    size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False))
    at = 0
    while at < batch.num_rows:
        before = size[at - 1] if at else 0
        end = max(at + 1, int(np.searchsorted(size, before + most_bytes, "right")))
        yield batch.slice(at, end - at)
        at = end


def solve_components(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node reachable) of all end points of the edges."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    left, right = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        x, y = label[left], label[right]
        open_ = x != y
        if not open_.any():
            return nodes, nodes[label]
        np.minimum.at(label, np.maximum(x, y)[open_], np.minimum(x, y)[open_])
        while not np.array_equal(label, jumped := label[label]):
            label = jumped


def _solve_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    t = list(batches)
    a, b = (np.concatenate([np.empty(0, np.int64), *(x.column(i).to_numpy(zero_copy_only=False) for x in t)]) for i in (0, 1))
    node, label = solve_components(a, b)
    yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(label)], ["node", "component"])


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select("b", "a"))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    near = down.join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b"))
    return near.union(least.select("u", "m")).where("a <> b").distinct()


def components(edges: DataFrame, one_task: int = ONE_TASK_EDGES) -> DataFrame:
    """Connected components of ``edges(a BIGINT, b BIGINT)`` as (node, component = smallest node).

    Nodes without an edge are not returned; self loops and repeated edges are harmless.
    While there are more than ``one_task`` edges, large-star and small-star rounds contract
    them over the cluster, each written to the shared folder; once few are left (a checked
    count) one task finishes. Nothing but counts reaches the driver.
    """
    edges = materialise(edges.where("a <> b").select("a", "b"), "edges")
    n, seen = edges.count(), None
    while n > one_task:
        turned = materialise(_small_star(_large_star(edges)), "edges")
        forget(edges)
        edges = turned
        state = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(state) == seen:
            stars = edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
            return stars.union(edges.select("b", "b").distinct())
        n, seen = state[0], tuple(state)
    ship_package(edges.sparkSession)
    return edges.coalesce(1).mapInArrow(_solve_batches, "node bigint, component bigint")
