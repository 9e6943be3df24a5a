"""Graph views of the given tables: ``edges(src, dst, weight)``, self loops out, duplicates merged."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from binflow.storage import table


def edge_weights(edges: DataFrame, n_vertices: int) -> DataFrame:
    """Whole weights in [1, log2 V] from the end points: 1 + (31 src + 17 dst) mod floor(log2 V)."""
    m = max(1, int(max(1, n_vertices)).bit_length() - 1)
    return edges.withColumn("weight", 1 + (31 * F.col("src") + 17 * F.col("dst")) % m)


def lines_chain(rows: DataFrame, part_by: str, order_by: list[str], id_col: str) -> DataFrame:
    """(src, dst): each row's id to the next one's within a group. One window sort."""
    w = Window.partitionBy(part_by).orderBy(*order_by)
    return rows.select(F.col(id_col).alias("src"), F.lead(id_col).over(w).alias("dst")).where("dst is not null and src <> dst")


def symmetrise(edges: DataFrame) -> DataFrame:
    """Both directions of every edge; the smallest weight of repeated ones."""
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")
    return edges.select("src", "dst", "weight").union(back).groupBy("src", "dst").agg(F.min("weight").alias("weight"))


def g_line_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines, n = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "part").count()
    return edge_weights(lines_chain(lines, "l_orderkey", ["l_linenumber", "l_partkey", "l_suppkey"], "l_partkey").distinct(), n)


def g_copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = lines.withColumnRenamed("l_partkey", "dst")
    pairs = lines.withColumnRenamed("l_partkey", "src").join(other, "l_orderkey").where("src <> dst")
    return pairs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight"))


def g_order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "orders").count()
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("src"), (F.col("l_partkey") + n).alias("dst")).distinct()
    return symmetrise(lines.withColumn("weight", F.lit(1).cast("bigint")))


def g_part_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "part").count()
    lines = table(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + n).alias("dst"))
    return symmetrise(lines.agg(F.count(F.lit(1)).alias("weight")))


def g_cust_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "customer").count()
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("src"))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", (F.col("l_suppkey") + n).alias("dst")).join(orders, "l_orderkey")
    return symmetrise(lines.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight")))


def event_ids(spark: SparkSession, sf_dir: str, order: str = "time") -> DataFrame:
    """(event_id, vid): ids by time, by (user, time) or by a hash."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    if order == "time":
        return events.select("event_id", F.col("event_id").alias("vid"))
    by = ["user_id", "ts", "event_id"] if order == "user" else [F.pmod(F.col("event_id") * 2654435761, F.lit(4294967296)), F.col("event_id")]
    from binflow.plans.layout import dense_ids

    return dense_ids(events, by).select("event_id", "vid")


def g_event_chain(spark: SparkSession, sf_dir: str, order: str = "time") -> DataFrame:
    chain = lines_chain(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], "event_id")
    if order != "time":
        ids = event_ids(spark, sf_dir, order)
        a, b = (ids.select(F.col("event_id").alias(c), F.col("vid").alias(f"{c}_vid")) for c in ("src", "dst"))
        chain = chain.join(a, "src").join(b, "dst").select(F.col("src_vid").alias("src"), F.col("dst_vid").alias("dst"))
    return chain.withColumn("weight", F.lit(1).cast("bigint"))


def g_user_handoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events")
    # the next event overall: ordered within time slices first, so that no single task sorts everything
    slices = events.withColumn("slice", F.date_trunc("day", "ts"))
    inner = Window.partitionBy("slice").orderBy("ts", "event_id")
    chained = slices.withColumn("next", F.lead("user_id").over(inner)).withColumn("place", F.row_number().over(inner))
    firsts = chained.where("place = 1").select("slice", F.col("user_id").alias("first"))
    following = firsts.select(F.lag("slice").over(Window.orderBy("slice")).alias("slice"), "first")  # one row a slice
    pairs = chained.join(following, "slice", "left").select(F.col("user_id").alias("src"), F.coalesce("next", "first").alias("dst"))
    return pairs.where("dst is not null and src <> dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight"))


def g_geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = {n: table(spark, sf_dir, n) for n in ("region", "nation", "customer", "supplier", "orders")}
    sizes = [t[n].count() for n in ("region", "nation", "customer", "supplier")]
    nation, customer, supplier, orders = (sum(sizes[: i + 1]) for i in range(4))
    parts = [t["nation"].select(F.col("n_regionkey").cast("bigint").alias("src"), (F.col("n_nationkey") + nation).cast("bigint").alias("dst")), t["customer"].select((F.col("c_nationkey") + nation).cast("bigint"), F.col("c_custkey") + customer), t["supplier"].select((F.col("s_nationkey") + nation).cast("bigint"), F.col("s_suppkey") + supplier), t["orders"].select(F.col("o_custkey") + customer, F.col("o_orderkey") + orders)]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out.distinct().withColumn("weight", F.lit(1).cast("bigint"))


def link_extract(pages: DataFrame) -> DataFrame:
    """(page_id, href): every href target of a page's html, repeats included."""
    found = F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)
    return pages.select("page_id", F.explode(found).alias("href"))


def host_of(url):
    return F.regexp_extract(url, "^[a-z]+://([^/]+)", 1)


def g_page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages, then distinct hrefs in order: page -> href."""
    from binflow.plans.layout import dense_ids

    pages = table(spark, sf_dir, "pages")
    n = pages.count()
    links = link_extract(pages).groupBy("page_id", "href").agg(F.count(F.lit(1)).alias("weight"))
    names = dense_ids(links.select("href").distinct(), ["href"]).select("href", (F.col("vid") + n).alias("dst"))
    return links.join(names, "href").select(F.col("page_id").alias("src"), "dst", "weight")


def g_host_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct hosts in order, then distinct hrefs: host -> href."""
    from binflow.plans.layout import dense_ids

    pages = table(spark, sf_dir, "pages").withColumn("host", host_of("url"))
    links = pages.select("host", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href"))
    links = links.groupBy("host", "href").agg(F.count(F.lit(1)).alias("weight"))
    hosts = dense_ids(pages.select("host").distinct(), ["host"]).select("host", F.col("vid").alias("src"))
    n = pages.select("host").distinct().count()
    names = dense_ids(links.select("href").distinct(), ["href"]).select("href", (F.col("vid") + n).alias("dst"))
    return links.join(hosts, "host").join(names, "href").select("src", "dst", "weight")


def g_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").withColumn("id", 8 * F.col("conv_id") + F.col("turn"))
    return lines_chain(turns, "conv_id", ["turn"], "id").withColumn("weight", F.lit(1).cast("bigint"))


def g_doc_dup(spark: SparkSession, sf_dir: str, least_chars: int = 60) -> DataFrame:
    """Star per shared line: every document with a line of ``least_chars`` to the smallest such document (same components as all pairs)."""
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line"))
    lines = lines.where(F.length("line") >= least_chars).select("doc_id", F.xxhash64("line").alias("h"), F.md5("line").alias("m"))
    first = lines.groupBy("h", "m").agg(F.min("doc_id").alias("dst"))
    pairs = lines.join(first, ["h", "m"]).where("doc_id <> dst").groupBy(F.col("doc_id").alias("src"), "dst")
    return symmetrise(pairs.agg(F.count(F.lit(1)).alias("weight")))


def g_embed_sim(spark: SparkSession, sf_dir: str, least: float = 0.3) -> DataFrame:
    """Both directions of the pairs of embeddings with one label and a cosine of ``least`` or more; ids are vec_ids."""
    from binflow.operators.relational import similarity_join

    pairs = similarity_join(table(spark, sf_dir, "embeddings").where("embedding is not null"), "vec_id", "embedding", "label", least)
    return symmetrise(pairs.select(F.col("a").alias("src"), F.col("b").alias("dst"), F.lit(1).cast("bigint").alias("weight")))


def g_doc_bench(spark: SparkSession, sf_dir: str, words: int = 8) -> DataFrame:
    """Documents, then benchmark items: both directions of the pairs that share a run of ``words`` words; weight: how many different ones."""
    from binflow.operators.relational import shingle_join

    docs, items = table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")
    n = docs.agg(F.max("doc_id")).first()[0] + 1
    pairs = shingle_join(docs, "doc_id", items, "item_id", "text", words)
    return symmetrise(pairs.select(F.col("a").alias("src"), (F.col("b") + n).alias("dst"), F.col("shared").alias("weight")))


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__[2:]: f for f in (g_line_chain, g_copurchase, g_order_part, g_part_supplier, g_cust_supplier, g_event_chain, g_user_handoff, g_geo_tree, g_page_links, g_host_links, g_turns, g_doc_dup, g_embed_sim, g_doc_bench)}


def register_views(spark: SparkSession, sf_dir: str) -> list[str]:
    """Every graph view as a temporary SQL view g_<name>(src, dst, weight); returns the names."""
    for name, view in VIEWS.items():
        view(spark, sf_dir).createOrReplaceTempView(f"g_{name}")
    return [f"g_{name}" for name in VIEWS]
