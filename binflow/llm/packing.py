"""Best-fit packing of documents into sequences of bounded length (operator 1)."""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from binflow.llm.bpe import Encoder
from binflow.llm.common import once_per_worker, share_model, slices, tokenizer_path
from binflow.llm.tokens import pack_ids
from binflow.storage import materialise

CAPACITY = 2048
END_ID = 0
_RANK_BITS = 44


def plan_counts(histogram: dict[int, int], capacity: int) -> np.ndarray:
    """Best-fit plan over counts of lengths, longest first.

    Returns runs (length, first rank, items per bin, first bin, bins, offset): the items of
    that length with ranks from ``first rank`` fill ``bins`` bins in a row, ``items per bin``
    each, from ``offset`` on. All bins that have the same room are one entry, so the work and
    the plan depend on the number of different lengths (at most ``capacity``), not on counts.
    """
    runs: list[tuple[int, int, int, int, int, int]] = []
    rooms: list[int] = []
    bins: dict[int, list[tuple[int, int]]] = {}
    opened = 0

    def give(room: int, first: int, n: int) -> None:
        if n and room:
            if room not in bins:
                bins[room] = []
                insort(rooms, room)
            bins[room].append((first, n))

    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        while left:
            at = bisect_left(rooms, length)
            if at == len(rooms):
                room, first = capacity, opened
                n = -(-left // (capacity // length))
                opened += n
            else:
                room = rooms[at]
                first, n = bins[room].pop()
                if not bins[room]:
                    del bins[room], rooms[at]
            each = room // length
            full = min(n, left // each)
            rest = left - full * each if full < n else 0
            if full:
                runs.append((length, rank, each, first, full, capacity - room))
                give(room - each * length, first, full)
            if rest:
                runs.append((length, rank + full * each, rest, first + full, 1, capacity - room))
                give(room - rest * length, first + full, 1)
            give(room, first + full + bool(rest), n - full - bool(rest))
            rank += full * each + rest
            left -= full * each + rest
    return np.array(runs, np.int64).reshape(-1, 6)


def cut(docs: DataFrame, id_col: str, text_col: str, capacity: int, path: str, end_id: int, with_tokens: bool) -> DataFrame:
    """Pieces of every document with the task that made them and their place among its pieces of that length."""
    shared = share_model(docs.sparkSession, path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = once_per_worker(("encoder", path), lambda: Encoder(shared.value))
        part, seen = TaskContext.get().partitionId(), np.zeros(capacity + 1, np.int64)
        for whole in batches:
            for batch in slices(whole, "text"):
                ids, n = coder.encode(batch.column(1).to_pylist())
                ids = np.insert(ids, np.cumsum(n), end_id)
                n = n + 1
                pieces = -(-n // capacity)
                row = np.repeat(np.arange(len(n)), pieces)
                piece = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
                first = n - (pieces - 1) * capacity
                start = np.where(piece == 0, 0, first[row] + (piece - 1) * capacity)
                length = np.where(piece == 0, first[row], capacity)
                order = np.argsort(length, kind="stable")
                runs = np.flatnonzero(np.r_[True, np.diff(length[order]) != 0])
                place = np.empty(len(row), np.int64)
                place[order] = np.arange(len(row)) - np.repeat(runs, np.diff(np.r_[runs, len(row)])) + seen[length[order]]
                seen += np.bincount(length, minlength=capacity + 1)
                begin = (np.cumsum(n) - n)[row] + start
                packed = memoryview(pack_ids(ids))
                raw = [packed[4 * a : 4 * b] for a, b in zip(begin.tolist(), (begin + length).tolist(), strict=True)]
                out = [batch.column(0).take(pa.array(row)), pa.array(piece, pa.int32()), pa.array(start), pa.array(length), pa.array([zlib.crc32(x) for x in raw], pa.int64()), pa.array(np.full(len(row), part)), pa.array(place)]
                if with_tokens:
                    out.append(pa.array([bytes(x) for x in raw], pa.binary()))
                yield pa.RecordBatch.from_arrays(out, names)

    names = ["id", "piece", "start", "length", "ids_crc32", "part", "place", *["tokens"] * with_tokens]
    picked = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    schema = f"id {dict(docs.dtypes)[id_col]}, piece int, start bigint, length bigint, ids_crc32 bigint, part bigint, place bigint"
    return picked.mapInArrow(run, schema + ", tokens binary" * with_tokens)


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, path: str | None = None, end_id: int = END_ID, with_tokens: bool = False) -> DataFrame:
    """Pack whole documents into sequences of at most ``capacity`` tokens.

    A document is its ids and then ``end_id``. Longer ones are cut into pieces of
    ``capacity``, the first piece taking what is over. Pieces are made once and written with
    their place among the task's pieces of that length; counts by (length, task) give every
    piece its rank within its length; the best-fit plan over the histogram (at most
    ``capacity`` lengths, made on the driver) gives that rank its sequence and offset.
    No document moves for that: only slim piece rows are joined.

    Returns (id, piece, start, length, ids_crc32, sequence_id, offset [, tokens]).
    Null and empty texts are the end id alone. Repeated rows are packed each on their own;
    a null id stays null; an empty table gives no rows; other columns are not read.
    """
    pieces = materialise(cut(docs, id_col, text_col, capacity, path or tokenizer_path(), end_id, with_tokens), "pieces")
    counts = pieces.groupBy("length", "part").agg(F.count(F.lit(1)).alias("n"))
    histogram = {r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    runs = plan_counts(histogram, capacity)
    runs = runs[np.lexsort((runs[:, 1], runs[:, 0]))]
    shared = docs.sparkSession.sparkContext.broadcast(runs)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plan = shared.value
        keys = (plan[:, 0] << _RANK_BITS) + plan[:, 1]
        for batch in batches:
            length, rank = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            run = plan[np.searchsorted(keys, (length << _RANK_BITS) + rank, "right") - 1]
            nth = rank - run[:, 1]
            kept = [batch.column(c) for c in names[: names.index("ids_crc32") + 1]]
            places = [pa.array(run[:, 3] + nth // run[:, 2]), pa.array(run[:, 5] + nth % run[:, 2] * length)]
            yield pa.RecordBatch.from_arrays([*kept, *places, *([batch.column("tokens")] if with_tokens else [])], names)

    names = ["id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", *["tokens"] * with_tokens]
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    first = counts.select("length", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"))
    ranked = pieces.join(first, ["length", "part"]).withColumn("rank", F.col("first") + F.col("place")).drop("first", "part", "place")
    schema = f"id {dict(docs.dtypes)[id_col]}, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint"
    return ranked.mapInArrow(place, schema + ", tokens binary" * with_tokens).withColumnRenamed("id", id_col)
