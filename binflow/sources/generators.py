"""Generated graphs: hash-driven scale-free edges and closed-form shapes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: share of edges that fall into the four quadrants at every level
QUADRANTS = (0.57, 0.19, 0.19, 0.05)


#: a prime below 2^31: squares of numbers below it fit a long
PRIME = (1 << 31) - 1


def rmat(spark: SparkSession, scale: int, degree: int = 16, seed: int = 42, quadrants: tuple[float, ...] = QUADRANTS) -> DataFrame:
    """2^scale vertices, degree * 2^scale draws of (src, dst); every bit pair comes from a hash of (draw, level, seed).

    Self loops are dropped and repeats merged, so the edge count is a little lower. The plan
    is a projection of ``range``: any task makes its own draws, and makes them again alike.
    """
    a, b, c, _ = quadrants
    rows = spark.range(degree << scale)
    # squaring and multiplying modulo a prime: the same numbers in any SQL engine
    rows = rows.select(*(((F.col("id") % PRIME * 48271 + (level + 1) * 69621 + seed) % PRIME).alias(f"x{level}") for level in range(scale)))
    for k in range(3):
        x = [F.col(f"x{level}") for level in range(scale)]
        rows = rows.select(*(((x[level] * x[level] + x[level] * (16807 + level) + 12345 + k) % PRIME).alias(f"x{level}") for level in range(scale)))
    src, dst = F.lit(0).cast("bigint"), F.lit(0).cast("bigint")
    for level in range(scale):
        u = F.col(f"x{level}") / float(PRIME)
        src = src * 2 + F.when(u >= a + b, 1).otherwise(0)
        dst = dst * 2 + F.when(((u >= a) & (u < a + b)) | (u >= a + b + c), 1).otherwise(0)
    return rows.select(src.alias("src"), dst.alias("dst")).where("src <> dst").distinct().withColumn("weight", F.lit(1).cast("bigint"))


def complete_graph(spark: SparkSession, n: int) -> DataFrame:
    """Every ordered pair of n vertices, numbered by a range."""
    pairs = spark.range(n * n).select(F.call_function("div", "id", F.lit(n)).alias("src"), (F.col("id") % n).alias("dst"))
    return pairs.where("src <> dst").withColumn("weight", F.lit(1).cast("bigint"))


def path_graph(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(max(0, n - 1)).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).cast("bigint").alias("weight"))


def cycle_graph(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst"), F.lit(1).cast("bigint").alias("weight"))


def star_graph(spark: SparkSession, n: int) -> DataFrame:
    """Hub 0 to and from n leaves."""
    out = spark.range(1, n + 1).select(F.lit(0).cast("bigint").alias("src"), F.col("id").alias("dst"), F.lit(1).cast("bigint").alias("weight"))
    return out.union(out.select("dst", "src", "weight"))


def grid_graph(spark: SparkSession, rows: int, cols: int) -> DataFrame:
    cells = spark.range(rows * cols)
    right = cells.where(F.col("id") % cols < cols - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    down = cells.where(F.col("id") < (rows - 1) * cols).select("id", F.col("id") + cols)
    one = right.union(down)
    return one.union(one.select("dst", "src")).withColumn("weight", F.lit(1).cast("bigint"))


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", **options) -> DataFrame:
    """Edge lists of any Spark format; csv and json get the schema (src, dst, weight), malformed rows are dropped unless ``mode`` says otherwise."""
    reader = spark.read.options(**({"mode": "DROPMALFORMED"} | options))
    if fmt in ("csv", "json"):
        reader = reader.schema("src bigint, dst bigint, weight bigint")
    rows = reader.format(fmt).load(path)
    return rows.select("src", "dst", F.coalesce("weight", F.lit(1)).cast("bigint").alias("weight") if "weight" in rows.columns else F.lit(1).cast("bigint").alias("weight"))
