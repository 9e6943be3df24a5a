"""Exact top-k inner products by norm buckets (operator 5)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from binflow.llm.neardup import is_finite_vector, matrix
from binflow.storage import materialise, ship_package

SCALE = 256
#: queries that are broadcast at once, rows of a norm bucket, longest vectors that give the first thresholds
QUERY_BLOCK, BUCKET, SEED_ROWS = 8192, 1024, 4096
QUERIES_AT_ONCE = 512
#: whole numbers below this are doubles
EXACT = 2.0**53
#: coordinate pruning is chosen where it leaves less than this share of a bucket
FEW = 0.1


def quantise(x: np.ndarray, scale: float = SCALE) -> np.ndarray:
    return np.floor(scale * x)


class Search:
    """Running top-k of a block of queries over buckets of candidates."""

    def __init__(self, query_ids: np.ndarray, queries: np.ndarray, k: int):
        self.query_ids, self.queries, self.k = query_ids, queries, k
        self.norms = np.linalg.norm(queries, axis=1)
        self.least = np.full(len(queries), -np.inf)
        self.found = [np.empty(0, np.int64) for _ in range(3)]

    def reduce(self) -> None:
        """Keep the k best of each query, ties to the smaller id, and raise the thresholds."""
        q, ids, score = self.found
        order = np.lexsort((ids, -score, q))
        q, ids, score = q[order], ids[order], score[order]
        first = np.r_[0, np.flatnonzero(np.diff(q)) + 1] if len(q) else np.empty(0, np.int64)
        rank = np.arange(len(q)) - np.repeat(first, np.diff(np.r_[first, len(q)]))
        last = rank == self.k - 1
        # a double below the score, where the score is no double itself
        self.least[q[last]] = np.maximum(self.least[q[last]], np.where(np.abs(score[last]) < EXACT, score[last], score[last] - np.abs(score[last]) * 1e-15))
        self.found = [v[rank < self.k] for v in (q, ids, score)]

    def _keep(self, q: np.ndarray, ids: np.ndarray, score: np.ndarray) -> None:
        other = ids != self.query_ids[q]
        self.found = [np.concatenate([a, b[other]]) for a, b in zip(self.found, (q, ids, score), strict=True)]

    def scan(self, ids: np.ndarray, x: np.ndarray) -> None:
        """Compare candidates, longest first, bucket by bucket."""
        norms = np.linalg.norm(x, axis=1)
        if len(norms) and len(self.norms) and float(norms.max()) * float(self.norms.max()) >= 2.0**63:
            raise OverflowError("an inner product may not fit a long")
        order = np.argsort(-norms, kind="stable")
        for at in range(0, len(order), BUCKET):
            rows = order[at : at + BUCKET]
            for first in range(0, len(self.queries), QUERIES_AT_ONCE):
                self._bucket(ids[rows], x[rows], norms[rows], np.arange(first, min(first + QUERIES_AT_ONCE, len(self.queries))))
            if len(self.found[0]) > 4 * self.k * len(self.queries):
                self.reduce()
        self.reduce()

    def _exact(self, q: np.ndarray, x: np.ndarray, pairs: bool) -> np.ndarray:
        """Inner products of queries with rows, of each pair or of all; in whole numbers where doubles would round (what wraps on the way comes back)."""
        a, how = self.queries[q], "ij,ij->i" if pairs else "ij,kj->ik"
        if len(x) and float(np.abs(a).max(initial=0)) * float(np.abs(x).max(initial=0)) * x.shape[1] >= EXACT:
            return np.einsum(how, a.astype(np.int64), x.astype(np.int64))
        return (np.einsum(how, a, x) if pairs else a @ x.T).astype(np.int64)

    def _bucket(self, ids: np.ndarray, x: np.ndarray, norms: np.ndarray, q: np.ndarray) -> None:
        """``norms`` falls. The local threshold of a query is the cosine that the longest row here would need."""
        scale = self.norms[q] * norms[0]
        with np.errstate(divide="ignore", invalid="ignore"):
            local = np.where(scale > 0, self.least[q] / scale, np.where(self.least[q] > 0, np.inf, -np.inf))
            alive = local <= 1 + 1e-12
            q, local = q[alive], local[alive]
            if not len(q):
                return
            reach = np.where(self.least[q] > 0, self.least[q] / self.norms[q], -np.inf)
        prefix = np.searchsorted(-norms, -reach * (1 - 1e-12), "right")
        longest = int(prefix.max())
        if not longest:
            return
        if (local > 0).all() and norms[-1] > 0:
            focus = np.argmax(np.abs(self.queries[q]), axis=1)
            part = self.queries[q, focus] / self.norms[q]
            t = np.minimum(local, 1)
            spread = np.sqrt(np.maximum(0, (1 - part**2) * (1 - t**2)))
            unit = x / norms[:, None]
            left = np.empty(len(q), np.int64)
            right, sorted_rows = left.copy(), {}
            for f in np.unique(focus).tolist():
                sorted_rows[f] = by = np.argsort(unit[:, f], kind="stable")
                of = focus == f
                # where the focus alone exceeds the threshold, there is no upper border
                high = np.where(part[of] >= t[of], 2.0, part[of] * t[of] + spread[of] + 1e-9)
                low = np.where(part[of] <= -t[of], -2.0, part[of] * t[of] - spread[of] - 1e-9)
                left[of] = np.searchsorted(unit[by, f], low)
                right[of] = np.searchsorted(unit[by, f], high, "right")
            if (n := right - left).mean() < FEW * longest:
                at = np.repeat(left - np.cumsum(n) + n, n) + np.arange(int(n.sum()))
                who = np.repeat(np.arange(len(q)), n)
                rows = np.empty(len(at), np.int64)
                for f, by in sorted_rows.items():
                    of = focus[who] == f
                    rows[of] = by[at[of]]
                score = self._exact(q[who], x[rows], True)
                good = score >= self.least[q[who]]
                self._keep(q[who[good]], ids[rows[good]], score[good])
                return
        score = self._exact(q, x[:longest], False)
        who, row = np.nonzero(score >= self.least[q][:, None])
        self._keep(q[who], ids[row], score[who, row])


def top_k(vectors: DataFrame, is_query, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", scale: float = SCALE) -> DataFrame:
    """(query_id, rank, id, score): the ``k`` largest integer inner products of every query with all other rows.

    Components become floor(scale * x). Queries (rows for which the column ``is_query`` holds)
    are broadcast in blocks of about QUERY_BLOCK; for each block all candidates are read once,
    nothing else moves. A bounded number of the longest vectors gives every query its first
    threshold. The table is dealt and sorted by length once, so that every bucket holds vectors
    of similar length wherever they came from; for each bucket and query the cosine needed by
    the bucket's longest row decides: above 1 the bucket is skipped, else it is cut by length
    or by the feasible range of the query's largest coordinate, and what is left is verified.
    Each task keeps k rows per query; a window over those gives the result.

    Scores are exact up to the range of a long; where an inner product might leave it, that is
    an error.

    Ties go to the smaller id. Vectors that are null or hold null or non-finite components,
    and rows with a null id, take no part; rows with the query's own id are not its
    candidates; of repeated query rows one counts, repeated candidates count each. Shorter
    vectors count as filled up with zeros. An empty table gives no rows.
    """
    spark = vectors.sparkSession
    ship_package(spark)
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vector_col).alias("vec"), F.coalesce(is_query, F.lit(False)).alias("asks"))
    rows = rows.where(F.col("id").isNotNull() & F.coalesce(is_finite_vector(F.col("vec")), F.lit(False)))
    queries = rows.where("asks").dropDuplicates(["id"]).select("id", "vec")
    size = rows.agg(F.count(F.when(F.col("asks"), 1)).alias("n"), F.coalesce(F.max(F.size("vec")), F.lit(1)).alias("dim")).first()
    blocks, dim = max(1, -(-size.n // QUERY_BLOCK)), max(1, size.dim)
    norm = F.aggregate("vec", F.lit(0.0), lambda a, x: a + F.pow(F.floor(x.cast("double") * scale).cast("double"), 2))
    sized = rows.select("id", "vec", norm.alias("norm"))
    # equal lengths are told apart by the id's hash, so that many copies of a vector do not fill one range
    by_length = sized.repartitionByRange(F.col("norm").desc(), F.xxhash64("id")).sortWithinPartitions(F.col("norm").desc())
    buckets = materialise(by_length.select("id", "vec", "norm"), "buckets")
    longest = buckets.orderBy(F.col("norm").desc(), "id").limit(SEED_ROWS).select("id", "vec").toArrow()
    seed_ids, seed_rows = _arrays(longest, dim, scale)
    parts = []
    for block in range(blocks):
        mine = queries if blocks == 1 else queries.where(F.pmod(F.xxhash64("id"), F.lit(blocks)) == block)
        query_ids, query_rows = _arrays(mine.toArrow(), dim, scale)
        first = Search(query_ids, query_rows, k)
        first.scan(seed_ids, seed_rows)
        shared = spark.sparkContext.broadcast((query_ids, query_rows, first.least))
        parts.append(materialise(_block(buckets.select("id", "vec"), shared, k, dim, scale), "top"))
    out = parts[0]
    for more in parts[1:]:
        out = out.union(more)
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "id")
    best = out.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return best.select("query_id", "rank", F.col("id").alias(id_col), "score")


def _arrays(t: pa.Table, dim: int, scale: float) -> tuple[np.ndarray, np.ndarray]:
    if not t.num_rows:
        return np.empty(0, np.int64), np.empty((0, dim))
    t = t.combine_chunks()
    return t.column("id").to_numpy().astype(np.int64), quantise(matrix(t.column("vec").chunk(0), dim), scale)


def _block(rows: DataFrame, shared, k: int, dim: int, scale: float) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        query_ids, queries, least = shared.value
        search = Search(query_ids, queries, k)
        search.least = least.copy()
        for batch in batches:
            search.scan(batch.column(0).to_numpy(), quantise(matrix(batch.column(1), dim), scale))
        q, ids, score = search.found
        yield pa.RecordBatch.from_arrays([pa.array(query_ids[q]), pa.array(ids), pa.array(score.astype(np.int64))], ["query_id", "id", "score"])

    return rows.mapInArrow(run, "query_id bigint, id bigint, score bigint")
