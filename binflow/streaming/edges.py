"""Streams of events as edge counts."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from binflow.operators.graphs import alternating_stars
from binflow.sources import views
from binflow.storage import materialise, new_folder, ship_package, table


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as a stream of all available files, with ``ts`` in UTC whatever the session's zone."""
    schema = table(spark, sf_dir, "events").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.timestamp_micros(F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01', ts)")))


def _plain(col: str):
    return F.expr(f"timestampadd(MICROSECOND, unix_micros({col}), timestamp_ntz'1970-01-01')")


def _drain(spark: SparkSession, rows: DataFrame, mode: str, at: str | None = None) -> DataFrame:
    """Run over what is there and read the result; one file set a batch, written over if a batch is run again.

    ``at``: a shared folder that holds the query's progress and result; a later run there goes
    on with the files that have come since. Without it every run starts anew.
    """
    out = at or new_folder(spark, "stream")
    done = rows.writeStream.outputMode(mode).option("checkpointLocation", f"{out}/log").trigger(availableNow=True)

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/data" if mode == "complete" else f"{out}/data/batch={batch_id}")

    done.foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(rows.schema).parquet(f"{out}/data").select(rows.columns)


def window_counts(spark: SparkSession, sf_dir: str, late: str = "1 hour", width: str = "1 day", at: str | None = None) -> DataFrame:
    """(day, event_type, n): a watermarked tumbling window over the events read as a stream."""
    counts = _events(spark, sf_dir).withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return _drain(spark, counts, "complete", at).select(_plain("window.start").alias("day"), "event_type", "n")


def purchases_after_clicks(spark: SparkSession, sf_dir: str, late: str = "1 hour", span: str = "6 hours", at: str | None = None) -> DataFrame:
    """(click_id, purchase_id): two streams joined within a span of time; state older than the watermarks and the span is dropped."""
    clicks = _events(spark, sf_dir).where("event_type = 'click'").select(F.col("user_id").alias("u1"), F.col("ts").alias("t1"), F.col("event_id").alias("click_id")).withWatermark("t1", late)
    bought = _events(spark, sf_dir).where("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), F.col("event_id").alias("purchase_id")).withWatermark("t2", late)
    pairs = clicks.join(bought, F.expr(f"u1 = u2 and t2 >= t1 and t2 < t1 + interval {span}"))
    return _drain(spark, pairs.select("click_id", "purchase_id"), "append", at)


def _tally(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    n, last = state.get if state.exists else (0, 0)
    for batch in batches:
        n, last = n + len(batch), max(last, int(batch["us"].max()))
    state.update((n, last))
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last_us": [last]})


def vertex_activity(spark: SparkSession, sf_dir: str, at: str | None = None) -> DataFrame:
    """(user_id, n, last_us): out-degree in the stream of events and time of the last one, kept as state of each vertex."""
    ship_package(spark)
    rows = _events(spark, sf_dir).select("user_id", F.unix_micros("ts").alias("us"))
    kept = "n bigint, last_us bigint"
    counted = rows.groupBy("user_id").applyInPandasWithState(_tally, f"user_id bigint, {kept}", kept, "update", GroupStateTimeout.NoTimeout)
    updates = _drain(spark, counted, "update", at)
    return updates.groupBy("user_id").agg(F.max("n").alias("n"), F.max("last_us").alias("last_us"))


def sliding_counts(spark: SparkSession, sf_dir: str, late: str = "1 hour", width: str = "1 day", step: str = "6 hours", at: str | None = None) -> DataFrame:
    """(start, event_type, n) of overlapping windows."""
    counts = _events(spark, sf_dir).withWatermark("ts", late).groupBy(F.window("ts", width, step), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return _drain(spark, counts, "complete", at).select(_plain("window.start").alias("start"), "event_type", "n")


def session_counts(spark: SparkSession, sf_dir: str, late: str = "1 hour", gap: str = "2 hours", at: str | None = None) -> DataFrame:
    """(user_id, start, n): runs of a user's events with less than ``gap`` between neighbours."""
    counts = _events(spark, sf_dir).withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return _drain(spark, counts, "complete", at).select("user_id", _plain("s.start").alias("start"), "n")


def without_repeats(spark: SparkSession, sf_dir: str, late: str = "1 hour") -> DataFrame:
    """(event_id, event_type): each event once though the stream holds it twice within the watermark."""
    rows = _events(spark, sf_dir).withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).withWatermark("ts", late)
    return _drain(spark, rows.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"), "append")


def add_edges(labels: DataFrame | None, edges: DataFrame) -> DataFrame:
    """Labels (vid, label) after ``edges(src, dst)`` arrived: components of the labels' own graph, then one look-up.

    Only the new edges, with labels for ends, are solved; untouched vertices are joined once.
    """
    ends = edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()
    if labels is None:
        known = ends.select("vid", F.col("vid").alias("label"))
    else:
        known = labels.union(ends.join(labels, "vid", "left_anti").select("vid", F.col("vid").alias("label")))
    a, b = (known.select(F.col("vid").alias(c), F.col("label").alias(f"{c}_label")) for c in ("src", "dst"))
    short = edges.join(a, "src").join(b, "dst").select(F.col("src_label").alias("src"), F.col("dst_label").alias("dst")).distinct()
    merged = alternating_stars(short).select(F.col("vid").alias("label"), F.col("label").alias("to"))
    return known.join(merged, "label", "left").select("vid", F.coalesce("to", "label").alias("label"))


def incremental_components(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(vid, label) kept over the batches of a stream of ``edges(src, dst)``.

    Batch b reads the labels of batch b - 1 and writes those of b, so running one again gives
    the same table.
    """
    out, last = new_folder(spark, "labels"), {}

    def add(batch: DataFrame, batch_id: int) -> None:
        before = spark.read.parquet(f"{out}/{batch_id - 1}") if batch_id else None
        add_edges(before, materialise(batch.select("src", "dst"), "arrived")).write.mode("overwrite").parquet(f"{out}/{batch_id}")
        last["batch"] = batch_id

    edges.writeStream.option("checkpointLocation", f"{out}/log").trigger(availableNow=True).foreachBatch(add).start().awaitTermination()
    if not last:
        return spark.createDataFrame([], "vid bigint, label bigint")
    return spark.read.parquet(f"{out}/{last['batch']}")


def event_components(spark: SparkSession, sf_dir: str, files: int = 3) -> DataFrame:
    """Components of the chains of events that arrive as a stream of ``files`` files."""
    chain = views.g_event_chain(spark, sf_dir).select("src", "dst")
    path = new_folder(spark, "arrivals")
    chain.repartition(files, "src").write.parquet(path)
    return incremental_components(spark, spark.readStream.schema(chain.schema).option("maxFilesPerTrigger", 1).parquet(path))
