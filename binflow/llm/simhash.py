"""SimHash near-duplicates by anchor points of a covering code (operator 6).

A fingerprint has 64 bits. Two blocks of 23 bits are decoded with the perfect binary Golay
code, whose balls of radius 3 cover every word exactly once: the pair of code words is the
fingerprint's home anchor. Two fingerprints at distance d split their differing bits over the
blocks, so the home of one lies within radius 3 + e1 and 3 + e2 of the other's blocks with
e1 + e2 <= d. Every distinct fingerprint is replicated to those anchors and compared there
with the ones at home: each pair meets at one anchor, the home of its smaller member.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binflow.llm.common import components, slices
from binflow.storage import materialise, ship_package

SHINGLE, SEED, DISTANCE = 3, 42, 2
BLOCK, RADIUS, CHECK = 23, 3, 11
#: fixed value: generator polynomial of the binary Golay code of length 23
GENERATOR = 0xC75


def fingerprint(text: str | None, words: int = SHINGLE, seed: int = SEED) -> int:
    """64-bit SimHash of the word shingles of the A-Z-lower-cased text; 0 without words."""
    parts = (text or "").encode().lower().split()
    if not parts:
        return 0
    flat = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.r_[0, ends[:-1] + 1]
    width = min(words, len(parts))
    count = len(parts) - width + 1
    spans = zip(starts[:count].tolist(), ends[width - 1 :].tolist(), strict=True)
    hashes = np.fromiter((xxhash.xxh64_intdigest(flat[a:b], seed) for a, b in spans), np.uint64, count)
    votes = np.zeros(64, np.int64)
    for at in range(0, count, 1 << 15):
        bits = np.unpackbits(hashes[at : at + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        votes += bits.sum(axis=0, dtype=np.int64)
    return int(np.packbits(votes * 2 > count, bitorder="little").view(np.uint64)[0])


def _print_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in slices(whole, "text"):
            prints = np.array([fingerprint(x) for x in batch.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints)], ["id", "fp"])


def _remainder(v: int) -> int:
    for bit in range(BLOCK - 1, CHECK - 1, -1):
        if v >> bit & 1:
            v ^= GENERATOR << (bit - CHECK)
    return v


@lru_cache(1)
def _code_tables(distance: int):
    """Syndromes of byte values, and for each reach the error patterns of every syndrome within RADIUS + reach."""
    unit = np.array([_remainder(1 << i) for i in range(24)])
    values = np.arange(256)
    by_byte = [np.bitwise_xor.reduce(np.where(values[:, None] >> np.arange(8) & 1, unit[8 * k : 8 * k + 8], 0), axis=1) for k in range(3)]
    patterns, weights = [], []
    for w in range(RADIUS + distance + 1):
        c = np.array(list(combinations(range(BLOCK), w)), np.int64)
        patterns.append((np.int64(1) << c).sum(axis=1))
        weights.append(np.full(len(c), w))
    pattern, weight = np.concatenate(patterns), np.concatenate(weights)
    syndrome = by_byte[0][pattern & 255] ^ by_byte[1][pattern >> 8 & 255] ^ by_byte[2][pattern >> 16]
    reach = []
    for e in range(distance + 1):
        mine = weight <= RADIUS + e
        order = np.argsort(syndrome[mine], kind="stable")
        n = np.bincount(syndrome[mine], minlength=1 << CHECK)
        reach.append((pattern[mine][order], n, np.cumsum(n) - n))
    return by_byte, reach


def anchors(prints: np.ndarray, distance: int = DISTANCE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Home anchor of each fingerprint, and (row, anchor) of all anchors in reach, the home included."""
    by_byte, reach = _code_tables(distance)
    blocks = [(prints >> np.uint64(k * BLOCK) & np.uint64((1 << BLOCK) - 1)).astype(np.int64) for k in (0, 1)]
    syndromes = [by_byte[0][b & 255] ^ by_byte[1][b >> 8 & 255] ^ by_byte[2][b >> 16] for b in blocks]
    shift = BLOCK - CHECK

    def word(k: int, rows: np.ndarray, e: int, nth: np.ndarray) -> np.ndarray:
        pattern, _, first = reach[e]
        return (blocks[k][rows] ^ pattern[first[syndromes[k][rows]] + nth]) >> CHECK

    everyone = np.arange(len(prints))
    zero = np.zeros(len(prints), np.int64)
    home = word(0, everyone, 0, zero) << shift | word(1, everyone, 0, zero)
    keys = []
    for e in range(distance + 1):
        n0, n1 = reach[e][1][syndromes[0]], reach[distance - e][1][syndromes[1]]
        n = n0 * n1
        row = np.repeat(everyone, n)
        nth = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
        anchor = word(0, row, e, nth // n1[row]) << shift | word(1, row, distance - e, nth % n1[row])
        keys.append(row << (2 * shift) | anchor)
    key = np.unique(np.concatenate(keys))
    return home, key >> (2 * shift), key & ((1 << 2 * shift) - 1)


def _replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for at in range(0, whole.num_rows, 2000):
            fp = whole.column(0).to_numpy(zero_copy_only=False)[at : at + 2000]
            _, row, anchor = anchors(fp.view(np.uint64))
            yield pa.RecordBatch.from_arrays([pa.array(anchor.astype(np.int32)), pa.array(fp[row])], ["anchor", "near"])


def _at_home(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        fp = batch.column(0).to_numpy(zero_copy_only=False)
        home, _, _ = anchors(fp.view(np.uint64), 0)
        yield pa.RecordBatch.from_arrays([pa.array(home.astype(np.int32)), pa.array(fp)], ["anchor", "fp"])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp BIGINT) of every row; the fingerprint's bits are those of the unsigned number."""
    ship_package(docs.sparkSession)
    picked = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    return picked.mapInArrow(_print_batches, f"id {dict(docs.dtypes)[id_col]}, fp bigint").withColumnRenamed("id", id_col)


def links(distinct: DataFrame) -> DataFrame:
    """All pairs (fp, near) with fp < near of distinct fingerprints at DISTANCE bits or fewer.

    A fingerprint has at most 2,080 others within two bits, so links grow with the number of
    different fingerprints, however many documents share one. The sides are shuffled at every
    size: Spark takes the replicas, some 60 rows a fingerprint, to be as few as the
    fingerprints and would broadcast them.
    """
    home = distinct.select("fp").mapInArrow(_at_home, "anchor int, fp bigint")
    near = distinct.select("fp").mapInArrow(_replicate, "anchor int, near bigint")
    close = (F.col("fp") < F.col("near")) & (F.bit_count(F.col("fp").bitwiseXOR(F.col("near"))) <= DISTANCE)
    return home.join(near.hint("merge"), "anchor").where(close).select("fp", "near")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp BIGINT, component_id): groups of documents linked by fingerprints at two bits or fewer.

    ``component_id`` is the smallest id reachable. Texts that are null, empty or blank have
    fingerprint 0 and are linked like others. Rows keep their number: repeated ids stay. Rows
    with a null id take part; they get the smallest id of their group, or null if it has none.
    An empty table gives no rows; other columns are not read.
    """
    prints = materialise(fingerprints(docs, id_col, text_col), "prints")
    heads = materialise(prints.groupBy("fp").agg(F.min(id_col).alias("head")), "heads")
    found = components(links(heads).select(F.col("fp").alias("a"), F.col("near").alias("b")))
    grouped = heads.join(found, heads["fp"] == found["node"], "left").select("fp", "head", F.coalesce("component", "fp").alias("group"))
    smallest = grouped.groupBy("group").agg(F.min("head").alias("component_id"))
    return prints.join(grouped.join(smallest, "group").select("fp", "group", "component_id"), "fp").select(id_col, "fp", "group", "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose id is the smallest of its group of near-duplicates, all columns kept.

    Rows that share one id and are kept count as one document: one of them stays. A row with
    a null id stays only if its group has no id at all, one row of each such group.
    """
    columns = docs.columns
    groups = materialise(near_duplicates(docs, id_col, text_col), "groups")
    by_id = groups.where(F.col(id_col).isNotNull()).groupBy(id_col).agg(F.max(F.col(id_col) == F.col("component_id")).alias("kept"), F.count(F.lit(1)).alias("copies"))
    # the ids that go, or need a second look, are the smaller side of this join
    other = materialise(by_id.where("not kept or copies > 1"), "other")
    single = docs.where(F.col(id_col).isNotNull()).join(other.select(id_col), id_col, "left_anti").select(columns)
    several = docs.join(other.where("kept").select(id_col), id_col, "left_semi").dropDuplicates([id_col]).select(columns)
    out = single.unionByName(several)
    nameless = groups.where("component_id is null").select("fp", "group").distinct()
    if nameless.limit(1).count():
        print_of = F.pandas_udf(lambda texts: texts.map(lambda x: np.uint64(fingerprint(x)).astype(np.int64)).astype("int64"), "bigint")
        rows = docs.where(F.col(id_col).isNull()).withColumn("__fp", print_of(F.coalesce(text_col, F.lit(""))))
        rows = rows.join(nameless.select(F.col("fp").alias("__fp"), F.col("group").alias("__group")), "__fp").dropDuplicates(["__group"])
        out = out.unionByName(rows.select(columns))
    return out
