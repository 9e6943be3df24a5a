"""Relational operators around the graph methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, ts: str, values: list[str]) -> DataFrame:
    """``left`` with the values of the latest earlier-or-equal row of ``right``: one union and one window sort a key, no range join."""
    marked = left.select("*", F.lit(1).alias("__side")).unionByName(right.select(by, ts, *values, F.lit(0).alias("__side")), allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(ts, "__side").rowsBetween(Window.unboundedPreceding, 0)
    last = {f"last_{v}": F.last(F.when(F.col("__side") == 0, F.col(v)), ignorenulls=True).over(w) for v in values}
    return marked.withColumns(last).where("__side = 1").select(*left.columns, *last)


def interval_join(left: DataFrame, right: DataFrame, by: list[str], at: str, of: str, span: int) -> DataFrame:
    """Pairs with right.of in [left.at, left.at + span): equi-join on buckets of ``span``, each left row in two, then the exact test."""
    a = left.withColumn("__b", F.explode(F.array(F.floor(F.col(at) / span), F.floor(F.col(at) / span) + 1)))
    b = right.withColumn("__b", F.floor(F.col(of) / span))
    return a.join(b, [*by, "__b"]).where((F.col(of) >= F.col(at)) & (F.col(of) < F.col(at) + span)).drop("__b")


def range_join(rows: DataFrame, col: str, width: int) -> DataFrame:
    """Index of the equal range that a value falls in."""
    return rows.withColumn("range_id", F.floor(F.col(col) / width))


def top_k(rows: DataFrame, col: str, k: int, by: list[str] | None = None, ties: str = "vid") -> DataFrame:
    """The k largest rows, overall or by group."""
    if not by:
        return rows.orderBy(F.col(col).desc(), ties).limit(k)
    order = Window.partitionBy(*by).orderBy(F.col(col).desc(), ties)
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def prefix_sum(rows: DataFrame, by: list[str], order: list[str], col: str) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("running", F.sum(col).over(w))


def semi(rows: DataFrame, keys: DataFrame) -> DataFrame:
    return rows.join(keys, keys.columns, "left_semi")


def anti(rows: DataFrame, keys: DataFrame) -> DataFrame:
    return rows.join(keys, keys.columns, "left_anti")


def degrees(edges: DataFrame) -> DataFrame:
    """(vid, in_deg, out_deg) of vertices with an edge."""
    out = edges.groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("out_deg"))
    into = edges.groupBy(F.col("dst").alias("vid")).agg(F.count(F.lit(1)).alias("in_deg"))
    return out.join(into, "vid", "full_outer").select("vid", F.coalesce("in_deg", F.lit(0)).alias("in_deg"), F.coalesce("out_deg", F.lit(0)).alias("out_deg"))


def path_to_root(parents: DataFrame, vid: int, max_steps: int = 64) -> list[int]:
    """Vertices from ``vid`` up the tree; one point look-up a step."""
    path = [vid]
    for _ in range(max_steps):
        row = parents.where(F.col("vid") == path[-1]).select("parent").first()
        if row is None or row.parent == path[-1]:
            break
        path.append(row.parent)
    return path


def random_read_share(edges: DataFrame, n_vertices: int, line: int = 64, id_bytes: int = 4, value_bytes: int = 4) -> DataFrame:
    """Share of a pull round's memory traffic that reads of neighbours' values take if each read moves one cache line."""
    reads = F.count(F.lit(1)) * line
    rest = F.count(F.lit(1)) * id_bytes + F.lit(n_vertices * (id_bytes + value_bytes))
    return edges.agg(F.round(reads / (reads + rest), 9).alias("share"))


def similarity_join(rows: DataFrame, id_col: str, vector_col: str, block_col: str, least: float) -> DataFrame:
    """(a, b, cosine): pairs a < b of one block whose cosine is ``least`` or more. A block is meant to be small: its pairs are formed."""
    unit = F.transform(vector_col, lambda x: x.cast("double"))
    one = rows.select(F.col(id_col).alias("id"), F.col(block_col).alias("block"), unit.alias("v"))
    one = one.withColumn("norm", F.sqrt(F.aggregate("v", F.lit(0.0), lambda acc, x: acc + x * x))).where("norm > 0")
    a, b = (one.select("block", *(F.col(c).alias(f"{c}_{side}") for c in ("id", "v", "norm"))) for side in "ab")
    dot = F.aggregate(F.zip_with("v_a", "v_b", lambda x, y: x * y), F.lit(0.0), lambda acc, x: acc + x)
    pairs = a.join(b, "block").where("id_a < id_b").select(F.col("id_a").alias("a"), F.col("id_b").alias("b"), (dot / (F.col("norm_a") * F.col("norm_b"))).alias("cosine"))
    return pairs.where(F.col("cosine") >= least)


def shingles(rows: DataFrame, id_col: str, text_col: str, words: int) -> DataFrame:
    """(id, shingle): the different runs of ``words`` blank-separated lower-case words of each text."""
    parts = F.filter(F.split(F.lower(F.col(text_col)), "[ \\t\\r\\n]+"), lambda w: w != "")
    runs = F.when(F.size("w") >= words, F.transform(F.sequence(F.lit(1), F.size("w") - words + 1), lambda i: F.array_join(F.slice("w", i, words), " ")))
    return rows.where(F.col(text_col).isNotNull()).select(F.col(id_col).alias("id"), parts.alias("w")).select("id", F.explode(F.array_distinct(runs)).alias("shingle"))


def shingle_join(left: DataFrame, left_id: str, right: DataFrame, right_id: str, text_col: str = "text", words: int = 8, least: int = 1) -> DataFrame:
    """(a, b, shared): how many different word runs two texts share. The right side's runs are looked up; a run's holders on the left are not paired with each other."""
    a = shingles(left, left_id, text_col, words).withColumnRenamed("id", "a")
    b = shingles(right, right_id, text_col, words).withColumnRenamed("id", "b")
    return a.join(b, "shingle").groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared")).where(F.col("shared") >= least)


def union_ids(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of either side, each once."""
    return a.union(b).distinct()


def intersect_ids(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.intersect(b)


def except_ids(a: DataFrame, b: DataFrame, keep_repeats: bool = False) -> DataFrame:
    return a.exceptAll(b) if keep_repeats else a.subtract(b)


def hash_sample(rows: DataFrame, id_col: str, share: float) -> DataFrame:
    """The rows whose id's hash falls below ``share``: the same rows at every run and whatever the partitioning."""
    h = (F.col(id_col) % 65521 * 40503 + 12289) % 65536
    return rows.where(h < int(share * 65536))


def histogram(rows: DataFrame, col: str, width: int) -> DataFrame:
    """(low, n) of equal ranges."""
    low = F.call_function("div", F.col(col), F.lit(width)) * width
    return rows.groupBy(low.alias("low")).agg(F.count(F.lit(1)).alias("n"))


def moving_mean(rows: DataFrame, by: list[str], order: str, col: str, before: int) -> DataFrame:
    """``mean`` of a row and up to ``before`` rows ahead of it."""
    w = Window.partitionBy(*by).orderBy(order).rowsBetween(-before, 0)
    return rows.withColumn("mean", F.avg(col).over(w))
