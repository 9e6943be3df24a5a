"""Index partitioning, message bins and their statistics."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from binflow.storage import forget, hadoop_path, materialise

#: ids of one list of a bin; lists of hubs are cut by ranges of this width
CHUNK = 1 << 16


def choose_k(n_vertices: int, state_bytes: int = 24, task_bytes: int = 128 << 20, slots: int = 8, factor: int = 4) -> int:
    """Smallest number of partitions whose state fits a task's memory and that keeps ``factor`` partitions a slot."""
    return max(1, -(-n_vertices * state_bytes // task_bytes), factor * slots)


def width(n_vertices: int, k: int) -> int:
    return max(1, -(-n_vertices // k))


def part_of(vid: Column | str, q: int) -> Column:
    """Number of the index range that an id lies in (whole-number division)."""
    return F.call_function("div", F.col(vid) if isinstance(vid, str) else vid, F.lit(q).cast("bigint")).cast("int")


def dense_ids(rows: DataFrame, order: list) -> DataFrame:
    """Add ``vid``: the rank of each row in ``order``, from 0, without a global sort in one task.

    The range-partitioned rows are written once, so that the ranges cannot move; each range is
    ranked on its own, and the sizes of the ranges (one row each) give its offset.
    """
    spark = rows.sparkSession
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ranged = rows.withColumn("__order", F.struct(*order)).repartitionByRange(n, "__order").withColumn("__p", F.spark_partition_id())
    ranged = materialise(ranged, "ranged")
    firsts, total = [], 0
    for r in ranged.groupBy("__p").agg(F.count(F.lit(1)).alias("n")).orderBy("__p").collect():  # one row a range
        firsts.append((r["__p"], total))
        total += r["n"]
    starts = F.broadcast(spark.createDataFrame(firsts, "__p int, __first bigint"))
    w = Window.partitionBy("__p").orderBy("__order")
    placed = ranged.join(starts, "__p").withColumn("vid", F.row_number().over(w) - 1 + F.col("__first"))
    return placed.select(*rows.columns, "vid")


def relabel(edges: DataFrame, order: str = "natural") -> tuple[DataFrame, DataFrame]:
    """Edges over dense ids, and the (key, vid) table. ``order``: natural, hash, or degree (largest first)."""
    keys = edges.select(F.col("src").alias("key")).union(edges.select("dst"))
    counted = keys.groupBy("key").agg(F.count(F.lit(1)).alias("degree"))
    by = {"natural": ["key"], "hash": [F.xxhash64("key").alias("h"), "key"], "degree": [(-F.col("degree")).alias("d"), "key"]}[order]
    ids = dense_ids(counted, by).select("key", "vid")
    a, b = (ids.select(F.col("key").alias(c), F.col("vid").alias(f"{c}_vid")) for c in ("src", "dst"))
    out = edges.join(a, "src").join(b, "dst").select(F.col("src_vid").alias("src"), F.col("dst_vid").alias("dst"), "weight")
    return out, ids


@dataclass
class Graph:
    """A static graph, cut into ``k`` index ranges of ``q`` ids.

    ``vertices(part, vid, deg, opd)``: out-degree and out-partition-degree (messages that a
    vertex makes). ``by_source`` and ``by_target`` hold the bins
    ``(src_part, dst_part, src, chunk, dst[], wt[])``, one row a message, dealt to the owner of
    either end, sorted, and kept: rounds join against them where they lie. ``part_stats``: one
    row a partition, with the range (lo, hi) of partitions that it can send to.
    """

    n_vertices: int
    k: int
    q: int
    vertices: DataFrame
    by_source: DataFrame
    by_target: DataFrame
    part_stats: DataFrame
    held: list[DataFrame] = field(default_factory=list)
    files: list[DataFrame] = field(default_factory=list)
    kept: dict = field(default_factory=dict)

    @property
    def bins(self) -> DataFrame:
        return self.by_source

    @property
    def edges(self) -> DataFrame:
        """(src, dst, weight) as given, from the bins."""
        return self.by_source.select("src", F.inline(F.arrays_zip("dst", "wt"))).withColumnRenamed("wt", "weight")

    def stats(self) -> dict[int, dict]:
        """``part_stats`` on the driver: k rows."""
        if "stats" not in self.kept:
            self.kept["stats"] = {r["part"]: r.asDict() for r in self.part_stats.collect()}
        return self.kept["stats"]

    def edges_by_source(self) -> DataFrame:
        """(src_part, src, dst, weight) with the owner of the source."""
        return self.by_source.select("src_part", "src", F.inline(F.arrays_zip("dst", "wt"))).withColumnRenamed("wt", "weight")

    def in_edges(self) -> DataFrame:
        """(src, dst, weight) dealt by target vertex and kept: the layout that pulling needs."""
        if "in" not in self.kept:
            self.kept["in"] = self.edges.repartition(self.k, "dst").persist()
            self.held.append(self.kept["in"])
        return self.kept["in"]

    def release(self) -> None:
        for df in self.held:
            df.unpersist()
        for df in self.files:
            forget(df)


def build_bins(edges: DataFrame, q: int) -> DataFrame:
    """Group edges by (source, target partition): the lists that a message carries, written once."""
    cut = edges.select("src", "dst", "weight", part_of("src", q).alias("src_part"), part_of("dst", q).alias("dst_part"))
    cut = cut.withColumn("chunk", F.floor((F.col("dst") - F.col("dst_part") * F.lit(q)) / CHUNK).cast("int"))
    lists = cut.groupBy("src_part", "dst_part", "src", "chunk").agg(F.sort_array(F.collect_list(F.struct("dst", "weight"))).alias("to"))
    return lists.select("src_part", "dst_part", "src", "chunk", F.col("to.dst").alias("dst"), F.col("to.weight").alias("wt"))


def out_partition_degree(bins: DataFrame) -> DataFrame:
    """(src, deg, opd): out-edges and messages of every vertex that has any."""
    each = bins.groupBy("src", "dst_part").agg(F.sum(F.size("dst")).alias("ids"))
    return each.groupBy("src").agg(F.sum("ids").alias("deg"), F.count(F.lit(1)).alias("opd"))


def placed_vertices(bins: DataFrame, n_vertices: int, q: int) -> DataFrame:
    """(vid, part, deg, opd) of the ids 0 .. n_vertices-1."""
    vertices = bins.sparkSession.range(n_vertices).select(F.col("id").alias("vid"), part_of("id", q).alias("part"))
    degrees = out_partition_degree(bins).withColumnRenamed("src", "vid")
    return vertices.join(degrees, "vid", "left").select("vid", "part", F.coalesce("deg", F.lit(0)).alias("deg"), F.coalesce("opd", F.lit(0)).alias("opd"))


def part_stats_of(vertices: DataFrame, bins: DataFrame) -> DataFrame:
    """(part, n_v, n_e, n_msg, r, lo, hi): r is messages over edges, at most 1; 1 without edges. lo and hi are the first and last partition that bins lead to."""
    sums = vertices.groupBy("part").agg(F.count(F.lit(1)).alias("n_v"), F.sum("deg").alias("n_e"), F.sum("opd").alias("n_msg"))
    reach = bins.groupBy(F.col("src_part").alias("part")).agg(F.min("dst_part").alias("lo"), F.max("dst_part").alias("hi"))
    return sums.join(reach, "part", "left").select("part", "n_v", "n_e", "n_msg", F.when(F.col("n_e") > 0, F.col("n_msg") / F.col("n_e")).otherwise(1.0).alias("r"), "lo", "hi")


def _laid_out(bins: DataFrame, vertices: DataFrame, n_vertices: int, k: int, q: int, files: list[DataFrame]) -> Graph:
    """Deal written bins and vertices to their owners and keep them. Lost blocks come back from the files."""
    by_source = bins.repartitionById(k, "src_part").sortWithinPartitions("src_part", "src").persist()
    by_target = bins.repartitionById(k, "dst_part").sortWithinPartitions("dst_part", "src_part", "src", "chunk").persist()
    vertices = vertices.select("part", "vid", "deg", "opd").repartitionById(k, "part").persist()
    stats = part_stats_of(vertices, by_source).persist()
    return Graph(n_vertices, k, q, vertices, by_source, by_target, stats, [by_source, by_target, vertices, stats], files)


def build(edges: DataFrame, n_vertices: int | None = None, k: int | None = None) -> Graph:
    """Partition a graph over dense ids 0 .. n_vertices-1. Self loops and parallel edges are kept as given.

    Ids outside the range are an error. The bins are written once to the shared folder.
    """
    spark = edges.sparkSession
    edges = edges.select("src", "dst", F.coalesce("weight", F.lit(1)).alias("weight") if "weight" in edges.columns else F.lit(1).cast("bigint").alias("weight"))
    if n_vertices is None:
        largest = edges.agg(F.max(F.greatest("src", "dst"))).first()[0]
        n_vertices = 0 if largest is None else largest + 1
    k = k or choose_k(n_vertices, slots=spark.sparkContext.defaultParallelism)
    q = width(n_vertices, k)
    inside = F.when((F.least("src", "dst") < 0) | (F.greatest("src", "dst") >= n_vertices), F.raise_error(F.concat(F.lit("vertex id out of range: "), F.col("src"), F.lit(" -> "), F.col("dst")))).otherwise(F.col("src"))
    bins = materialise(build_bins(edges.withColumn("src", inside), q), "bins")
    return _laid_out(bins, placed_vertices(bins, n_vertices, q), n_vertices, k, q, [bins])


def inter_partition_edges(edges: DataFrame, n_vertices: int, k: int) -> DataFrame:
    """(edges, crossing, share): edges whose ends lie in different partitions."""
    q = width(n_vertices, k)
    crossing = F.sum((part_of("src", q) != part_of("dst", q)).cast("bigint"))
    return edges.agg(F.count(F.lit(1)).alias("edges"), F.coalesce(crossing, F.lit(0)).alias("crossing")).withColumn("share", F.round(F.col("crossing") / F.col("edges"), 9))


def to_csr(edges: DataFrame) -> DataFrame:
    """(src, chunk, dst[], wt[]) sorted by target; a hub's list is cut by ranges of CHUNK targets. ``to_csc`` is the same by target."""
    lists = edges.groupBy("src", F.floor(F.col("dst") / CHUNK).alias("chunk")).agg(F.sort_array(F.collect_list(F.struct("dst", "weight"))).alias("to"))
    return lists.select("src", "chunk", F.col("to.dst").alias("dst"), F.col("to.weight").alias("wt"))


def to_csc(edges: DataFrame) -> DataFrame:
    return to_csr(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")).withColumnsRenamed({"src": "dst", "dst": "src"})


def from_csr(rows: DataFrame) -> DataFrame:
    return rows.select("src", F.inline(F.arrays_zip("dst", "wt"))).withColumnRenamed("wt", "weight")


def save_graph(graph: Graph, path: str) -> None:
    """Bins, one folder a source partition, vertices and a manifest (written last: a graph without it is not there)."""
    spark = graph.vertices.sparkSession
    graph.by_source.write.partitionBy("src_part").parquet(f"{path}/bins")
    graph.vertices.write.parquet(f"{path}/vertices")
    fs, p = hadoop_path(spark, f"{path}/manifest.json")
    stream = fs.create(p, False)
    stream.write(bytearray(json.dumps({"n_vertices": graph.n_vertices, "k": graph.k, "q": graph.q}).encode()))
    stream.close()


def open_graph(spark: SparkSession, path: str) -> Graph:
    about = json.loads(spark.read.text(f"{path}/manifest.json").first()[0])
    schema = "dst_part int, src bigint, chunk int, dst array<bigint>, wt array<bigint>, src_part int"
    bins = spark.read.schema(schema).parquet(f"{path}/bins").select("src_part", "dst_part", "src", "chunk", "dst", "wt")
    return _laid_out(bins, spark.read.parquet(f"{path}/vertices"), about["n_vertices"], about["k"], about["q"], [])
