"""Near-duplicate embeddings through a pivot-permutation index (operator 3).

A vector is described by its nearest reference points in order of nearness; the reference
points are vectors of the table. An inverted list holds the ids of the vectors that have its
point in their description. Two vectors are compared if their descriptions share enough
points: the lists count that on ids and descriptions alone, in the list of the smallest point
that both share, and only vectors that have a candidate are fetched and verified.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from binflow.llm.common import components, solve_components
from binflow.storage import forget, materialise, ship_package

THRESHOLD = 0.95
#: reference points that describe a vector, and how many of them two vectors must share
NEAREST, SHARED = 12, 5
#: the index is fitted on so many vectors of the table at most (their numbers fit 16 bits)
MOST_PIVOTS = 16_384
#: vectors drawn for each reference point, and the cosine from which two points are too close
DRAWN, APART = 2, 0.8
#: rows of one inverted list that are compared at once; longer lists are dealt out in pairs of blocks
BLOCK = 1024
PAIRS_AT_ONCE = 200_000
_LIST = "key int, lo int, hi int, upper boolean, id bigint"


def pivot_count(n_vectors: int) -> int:
    """About 4.5 times the square root of the number of vectors, a power of two, at most MOST_PIVOTS."""
    return min(MOST_PIVOTS, max(64, 1 << int(np.ceil(np.log2(4.5 * max(1, n_vectors) ** 0.5)))))


def is_finite_vector(vector: Column) -> Column:
    """True for a vector without null, NaN or infinite components; null for a null one."""
    return ~F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))


def matrix(column: pa.Array, dim: int) -> np.ndarray:
    """Rows of a list column as doubles, shorter ones filled up with zeros."""
    n = np.diff(column.offsets.to_numpy())
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    if (n == dim).all():
        return flat.reshape(-1, dim)
    out = np.zeros((len(n), dim))
    out[np.arange(dim) < n[:, None]] = flat
    return out


def unit(x: np.ndarray) -> np.ndarray:
    """Rows of length 1; the largest component is divided out first, so that no square overflows or vanishes."""
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1)[:, None]


def reference_points(drawn: np.ndarray, wanted: int, seed: int = 42) -> np.ndarray:
    """``wanted`` unit vectors: those of ``drawn`` that are no closer than APART to one taken before, filled up with random directions.

    Points that lie close together would be near to the same vectors in an order left to
    chance, so a dense group gets one point of its own and shares the others.
    """
    taken = np.empty((0, drawn.shape[1]))
    for at in range(0, len(drawn), 256):
        block = drawn[at : at + 256]
        free = (block @ taken.T).max(axis=1, initial=-1) < APART
        block = block[free]
        near, keep = block @ block.T >= APART, np.ones(len(block), bool)
        for i in range(len(block)):
            if keep[i]:
                keep[i + 1 :] &= ~near[i, i + 1 :]
        taken = np.concatenate([taken, block[keep]])[:wanted]
        if len(taken) == wanted:
            return taken
    return np.concatenate([taken, unit(np.random.default_rng(seed).normal(size=(wanted - len(taken), drawn.shape[1])))])


def nearest(x: np.ndarray, points: np.ndarray, k: int = NEAREST) -> np.ndarray:
    """Numbers of the ``k`` reference points nearest to each row, nearest first (ties: smaller number)."""
    near = x @ points.T
    k = min(k, len(points))
    some = np.sort(np.argpartition(-near, k - 1, axis=1)[:, :k], axis=1)
    order = np.argsort(-np.take_along_axis(near, some, axis=1), axis=1, kind="stable")
    return np.take_along_axis(some, order, axis=1)


def _describe(points: np.ndarray):
    dim = points.shape[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 2000):
                batch = whole.slice(at, 2000)
                near = nearest(unit(matrix(batch.column("vec"), dim)), points).astype("<i2")
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([r.tobytes() for r in near], pa.binary())], [*batch.schema.names, "near"])

    return run


def _postings(shared: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """(key, id, near): a vector stands in the lists of its points but for the ``shared`` - 1 largest numbers.

        The smallest of ``shared`` common points is never among those.
        """
        for batch in batches:
            near = _descriptions(batch.column("near"))
            each = np.sort(near, axis=1)[:, : max(1, near.shape[1] - shared + 1)]
            row = np.repeat(np.arange(len(near)), each.shape[1])
            yield pa.RecordBatch.from_arrays([pa.array(each.ravel().astype(np.int32)), batch.column("id").take(pa.array(row)), batch.column("near").take(pa.array(row))], ["key", "id", "near"])

    return run


def _descriptions(column: pa.Array) -> np.ndarray:
    """Rows of packed point numbers."""
    rows = column.to_pylist()
    return np.frombuffer(b"".join(rows), "<i2").reshape(len(rows), -1) if rows else np.empty((0, 1), "<i2")


def _pairs(sizes: np.ndarray, most: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(left, right) rows of all pairs within groups of adjacent rows, about ``most`` at once."""
    rest = np.repeat(np.cumsum(sizes), sizes) - np.arange(int(sizes.sum())) - 1
    total, at = np.cumsum(rest), 0
    while at < len(rest):
        end = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + most, "right")))
        left = np.repeat(np.arange(at, end), rest[at:end])
        first = np.cumsum(rest[at:end]) - rest[at:end]
        yield left, left + 1 + np.arange(len(left)) - np.repeat(first, rest[at:end])
        at = end


def candidates(near: np.ndarray, key: int, shared: int, side: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(left, right) rows of one list whose descriptions share ``shared`` points or more, ``key`` the smallest of them.

    Counted over the points above ``key``: rows that have one in common are adjacent there.
    ``side``: only rows of different sides are compared.
    """
    row, col = np.nonzero(near > key)
    point = near[row, col]
    order = np.lexsort((row, point))
    row, point = row[order], point[order]
    sizes = np.diff(np.r_[np.flatnonzero(np.r_[True, point[1:] != point[:-1]]), len(point)]) if len(point) else np.empty(0, np.int64)
    codes = []
    if shared < 2:  # the list itself is the shared point
        codes = [left * len(near) + right for left, right in _pairs(np.array([len(near)]), PAIRS_AT_ONCE)]
    else:
        for left, right in _pairs(sizes, 10 * PAIRS_AT_ONCE):
            a, b = row[left], row[right]
            if side is not None:
                cross = side[a] != side[b]
                a, b = a[cross], b[cross]
            codes.append(a * len(near) + b)
    found, count = np.unique(np.concatenate([np.empty(0, np.int64), *codes]), return_counts=True)
    if shared >= 2:
        found = found[count >= shared - 1]
    left, right = found // max(1, len(near)), found % max(1, len(near))
    if side is not None:
        left, right = left[side[left] != side[right]], right[side[left] != side[right]]
    if len(left):
        smaller = np.zeros(len(left), bool)
        for at in range(0, len(left), PAIRS_AT_ONCE):
            a, b = near[left[at : at + PAIRS_AT_ONCE]], near[right[at : at + PAIRS_AT_ONCE]]
            smaller[at : at + PAIRS_AT_ONCE] = ((a[:, :, None] == b[:, None, :]) & (a < key)[:, :, None]).any(axis=(1, 2))
        left, right = left[~smaller], right[~smaller]
    return left, right


def _by_list(handle: Callable[[pa.Table], Iterator[pa.RecordBatch]]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by (key, lo, hi); every such group reaches ``handle`` whole, one at a time."""
        kept: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            mark = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in ("key", "lo", "hi")])
            new = np.flatnonzero((mark[:, 1:] != mark[:, :-1]).any(axis=0)) + 1
            if kept and any(kept[-1].column(c)[-1].as_py() != v for c, v in zip(("key", "lo", "hi"), mark[:, 0].tolist(), strict=True)):
                yield from handle(pa.Table.from_batches(kept))
                kept = []
            at = 0
            for end in new.tolist():
                yield from handle(pa.Table.from_batches([*kept, batch.slice(at, end - at)]))
                kept, at = [], end
            kept.append(batch.slice(at))
        if kept:
            yield from handle(pa.Table.from_batches(kept))

    return run


def _group(t: pa.Table, shared: int) -> tuple[dict, np.ndarray, np.ndarray]:
    """Columns of one group, and its candidate pairs."""
    t = t.combine_chunks()
    col = {c: t.column(c).chunk(0) for c in t.schema.names}
    first = {c: col[c][0].as_py() for c in ("key", "lo", "hi")}
    side = None if first["lo"] == first["hi"] else col["upper"].to_numpy(zero_copy_only=False)
    left, right = candidates(_descriptions(col["near"]), first["key"], shared, side)
    return col, left, right


def _with_candidates(shared: int):
    def handle(t: pa.Table) -> Iterator[pa.RecordBatch]:
        """The members of a group that have a candidate in it."""
        if t.num_rows > 1:
            col, left, right = _group(t, shared)
            some = pa.array(np.unique(np.r_[left, right]))
            if len(some):
                yield pa.RecordBatch.from_arrays([col[c].take(some) for c in ("key", "lo", "hi", "upper", "id")], ["key", "lo", "hi", "upper", "id"])

    return _by_list(handle)


def _verify(dim: int, threshold: float, shared: int):
    def handle(t: pa.Table) -> Iterator[pa.RecordBatch]:
        """Link counts of the members of a group and a spanning forest of their links, never pairs."""
        col, left, right = _group(t, shared)
        ids, n = (col[c].to_numpy(zero_copy_only=False) for c in ("id", "n"))
        x = unit(matrix(col["vec"], dim))
        counts, a, b = np.zeros(len(x), np.int64), np.empty(0, np.int64), np.empty(0, np.int64)
        for at in range(0, len(left), PAIRS_AT_ONCE):
            i, j = left[at : at + PAIRS_AT_ONCE], right[at : at + PAIRS_AT_ONCE]
            linked = np.einsum("ij,ij->i", x[i], x[j]) >= threshold
            i, j = i[linked], j[linked]
            counts += np.bincount(i, n[j], minlength=len(x)).astype(np.int64) + np.bincount(j, n[i], minlength=len(x)).astype(np.int64)
            if len(i):
                node, label = solve_components(np.r_[a, ids[i]], np.r_[b, ids[j]])
                a, b = node[node != label], label[node != label]
        some = np.flatnonzero(counts)
        if len(some):
            out = [np.r_[ids[some], a], np.r_[ids[some], b], np.r_[counts[some], np.zeros(len(a), np.int64)]]
            yield pa.RecordBatch.from_arrays([pa.array(v) for v in out], ["a", "b", "links"])

    return _by_list(handle)


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", threshold: float = THRESHOLD, shared: int = SHARED) -> DataFrame:
    """(id, n_links, component_id, kept) of every vector: links are pairs with cosine >= threshold.

    Equal vectors become one with a count. The reference points are ``pivot_count`` vectors of
    the table, of those with the smallest hashes of their ids (see ``reference_points``); each
    vector is described by the NEAREST nearest of them. Vectors whose descriptions share ``shared`` points are verified in double precision.
    Lists hold ids and descriptions; those longer than BLOCK are dealt out as pairs of blocks.
    A list emits members, then counts and a spanning forest of its links, never pairs.
    No link below the threshold is reported; a true one is missed if the two share too few
    points (measured in README and tests; fewer ``shared`` points find more).

    Vectors that are null, zero or hold null or non-finite components, and rows with a null
    id, link with nothing: no links, their own component, kept. Shorter vectors count as
    filled up with zeros. Repeated rows are vectors of their own; an empty table gives no
    rows. Other columns are not read. Ids are whole numbers.
    """
    spark = vectors.sparkSession
    ship_package(spark)
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vector_col).alias("vec"))
    usable = F.coalesce(F.col("id").isNotNull() & is_finite_vector(F.col("vec")) & F.exists("vec", lambda x: x != 0), F.lit(False))
    plain = F.transform("vec", lambda x: x.cast("double") + 0.0)  # one zero, not two
    valid = rows.where(usable)
    distinct = materialise(valid.groupBy("vec").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("n")), "vectors")
    size = distinct.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("vec")).alias("dim")).first()
    dim, wanted = size.dim or 1, pivot_count(size.n)
    picked = distinct.orderBy(F.xxhash64("id"), "id").limit(DRAWN * wanted).select("vec").toArrow().combine_chunks()
    drawn = unit(matrix(picked.column("vec").chunk(0), dim)) if picked.num_rows else np.empty((0, dim))
    points = reference_points(drawn, wanted)
    shared = max(1, min(shared, len(points)))
    described = materialise(distinct.mapInArrow(_describe(points), f"{_schema(distinct)}, near binary"), "described")

    single = materialise(described.select("id", "near").mapInArrow(_postings(shared), "key int, id bigint, near binary"), "postings")
    lengths = single.groupBy("key").agg(F.count(F.lit(1)).alias("rows")).where("rows > 1")
    postings = single.join(F.broadcast(lengths), "key")  # MOST_PIVOTS rows at most
    blocks = F.ceil(F.col("rows") / BLOCK).cast("int")
    own = F.pmod(F.xxhash64("id"), blocks.cast("bigint")).cast("int")
    postings = postings.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    group = ("key", "lo", "hi")
    postings = postings.select("key", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), (F.col("own") > F.col("other")).alias("upper"), "id", "near")
    members = materialise(postings.repartition(*group).sortWithinPartitions(*group).mapInArrow(_with_candidates(shared), _LIST), "members")
    fetched = members.join(described, "id").select(*group, "upper", "id", "n", "near", "vec")
    found = materialise(fetched.repartition(*group).sortWithinPartitions(*group).mapInArrow(_verify(dim, threshold, shared), "a bigint, b bigint, links bigint"), "found")
    for done in (single, members, described):
        forget(done)

    counts = found.groupBy(F.col("a").alias("node")).agg(F.sum("links").alias("links"))
    groups = components(found.select("a", "b")).withColumnRenamed("node", "member")
    two = [F.xxhash64(plain).alias("h1"), F.xxhash64(F.lit(7), plain).alias("h2")]
    known = distinct.select("id", "n", *two).join(counts, F.col("id") == F.col("node"), "left").join(groups, F.col("id") == F.col("member"), "left")
    known = known.select("h1", "h2", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    # equal vectors meet by two 64-bit hashes: the vectors themselves do not travel again
    linked = valid.select("id", *two).join(known, ["h1", "h2"]).select("id", "n_links", "component_id")
    alone = rows.where(~usable).select("id", F.lit(0).cast("bigint").alias("n_links"), F.col("id").alias("component_id"))
    return linked.union(alone).select(F.col("id").alias(id_col), "n_links", "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(True)).alias("kept"))


def _schema(df: DataFrame) -> str:
    return ", ".join(f"{name} {kind}" for name, kind in df.dtypes)
