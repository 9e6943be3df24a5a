"""The registered graph, relational and streaming queries and their SQL."""

from __future__ import annotations

import math
import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from binflow import workloads
from binflow.baselines import runs as baselines
from binflow.operators import graphs as utilities
from binflow.operators import relational
from binflow.plans import engine, layout, misses, modes, program
from binflow.plans.layout import Graph
from binflow.programs import local, runs
from binflow.sources import views
from binflow.storage import materialise, table
from binflow.streaming import edges as streams

#: partitions of the registered graphs; threshold and rounds of the walks
K, SMALL_K, EPS, STEPS, TERMS = 16, 8, 1e-9, 20, 10
_GRAPHS: dict[tuple, Graph] = {}
Query = Callable[[SparkSession, str], DataFrame]


def _views(spark: SparkSession, sf_dir: str) -> dict[str, Callable[[], tuple[DataFrame, int | None]]]:
    both = lambda name: lambda: (views.symmetrise(views.VIEWS[name](spark, sf_dir)), None)
    parts = lambda: table(spark, sf_dir, "part").count()
    out = {name: (lambda name=name: (views.VIEWS[name](spark, sf_dir), None)) for name in ("host_links", "page_links", "geo_tree", "order_part", "part_supplier", "cust_supplier")}
    out |= {"copurchase": lambda: (views.VIEWS["copurchase"](spark, sf_dir), parts()), "event_chain": lambda: (views.VIEWS["event_chain"](spark, sf_dir), table(spark, sf_dir, "events").count())}
    out |= {"line_chain": lambda: (views.g_line_chain(spark, sf_dir), parts()), "line_both": lambda: (views.symmetrise(views.g_line_chain(spark, sf_dir)), parts())}
    return out | {"geo_both": both("geo_tree"), "turns_both": both("turns"), "page_both": both("page_links"), "host_both": both("host_links")}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A built view, kept for the session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _GRAPHS:
        _GRAPHS[key] = layout.build(*_views(spark, sf_dir)[name](), K)
    return _GRAPHS[key]


def bins_summary(spark, sf_dir):
    """Messages and ids of every bin. A message is a source's list for a partition, however many chunks it is kept in."""
    each = graph(spark, sf_dir, "line_chain").bins.groupBy("src_part", "dst_part", "src").agg(F.sum(F.size("dst")).alias("ids"))
    return each.groupBy("src_part", "dst_part").agg(F.count(F.lit(1)).alias("msgs"), F.sum("ids").alias("ids"))


def out_partition_degree(spark, sf_dir):
    return layout.out_partition_degree(graph(spark, sf_dir, "line_chain").bins)


def part_stats_r(spark, sf_dir):
    """Taken from the lines at every call: a kept graph has its k rows ready and would read no table."""
    edges, n = _views(spark, sf_dir)["line_chain"]()
    q = layout.width(n, K)
    bins = materialise(layout.build_bins(edges, q), "bins")
    return layout.part_stats_of(layout.placed_vertices(bins, n, q), bins).select("part", "n_v", "n_e", "n_msg", F.round("r", 9).alias("r"))


def mode_choice_all_active(spark, sf_dir):
    g = graph(spark, sf_dir, "line_chain")
    plan = modes.mode_plan(g.vertices, g.part_stats, g.k)
    return plan.select("part", "v_a", "e_a", F.round("cost_sc", 6).alias("cost_sc"), F.round("cost_pc", 6).alias("cost_pc"), "mode")


def _second_frontier(spark, sf_dir):
    g = graph(spark, sf_dir, "line_chain")
    return g, g.vertices.join(g.edges.where("src = 0").select(F.col("dst").alias("vid")).distinct(), "vid", "left_semi")


def mode_choice_bfs_round2(spark, sf_dir):
    g, active = _second_frontier(spark, sf_dir)
    plan = modes.mode_plan(active, g.part_stats, g.k)
    return plan.select("part", "v_a", "e_a", F.round("cost_sc", 6).alias("cost_sc"), F.round("cost_pc", 6).alias("cost_pc"), "mode")


def gather_list_round(spark, sf_dir):
    g, active = _second_frontier(spark, sf_dir)
    return g.bins.join(active.select(F.col("vid").alias("src")), "src").select("dst_part").distinct()


def bin_list_round(spark, sf_dir):
    g, active = _second_frontier(spark, sf_dir)
    return g.bins.join(active.select(F.col("vid").alias("src")), "src").select("dst_part", "src_part").distinct()


def _crossing(order: str) -> Query:
    def query(spark, sf_dir):
        n = table(spark, sf_dir, "events").count()
        return layout.inter_partition_edges(views.g_event_chain(spark, sf_dir, order), n, K)

    return query


def _bfs(name: str = "line_chain", root: int = 0, **how) -> Query:
    return lambda spark, sf_dir: runs.bfs(graph(spark, sf_dir, name), root, **how)


def _bfs_vertex(direction: str) -> Query:
    return lambda spark, sf_dir: baselines.bfs_switching(graph(spark, sf_dir, "line_chain"), 0, direction)[0]


def _sssp(**how) -> Query:
    return lambda spark, sf_dir: runs.sssp(graph(spark, sf_dir, "line_chain"), 0, **how)


def sssp_delta(spark, sf_dir):
    return baselines.sssp_delta(graph(spark, sf_dir, "line_chain"), 0)[0]


def sssp_topological(spark, sf_dir):
    return baselines.sssp_topological(graph(spark, sf_dir, "line_chain"), 0)[0]


def cc_geo_tree(spark, sf_dir):
    return runs.connected_components(graph(spark, sf_dir, "geo_both"))


def cc_turns(spark, sf_dir):
    turns = table(spark, sf_dir, "conversations").select((8 * F.col("conv_id") + F.col("turn")).alias("vid"))
    return runs.connected_components(graph(spark, sf_dir, "turns_both"), waves=1).join(turns, "vid", "left_semi")


def _ranks(name: str, mode: str) -> Query:
    def query(spark, sf_dir):
        return runs.pagerank(graph(spark, sf_dir, name), mode=mode).withColumn("rank", F.round("rank", 9))

    return query


def _ranks_by(paradigm: str) -> Query:
    def query(spark, sf_dir):
        out = engine.run(graph(spark, sf_dir, "line_chain"), program.pagerank(), paradigm=paradigm, max_rounds=10).state
        return out.select("vid", F.round("x", 9).alias("rank"))

    return query


def pagerank_residual(spark, sf_dir):
    return baselines.pagerank_residual(graph(spark, sf_dir, "line_chain"))[0]


def nibble_line_chain(spark, sf_dir):
    return runs.nibble(graph(spark, sf_dir, "line_both"), [0], EPS, STEPS).withColumn("p", F.round("p", 9))


def nibble_multi_seed(spark, sf_dir):
    return runs.nibble(graph(spark, sf_dir, "line_both"), [0, 1, 2], EPS, STEPS).withColumn("p", F.round("p", 9))


def sweep_cut(spark, sf_dir):
    g = graph(spark, sf_dir, "line_both")
    return runs.sweep_cut(g, runs.nibble(g, [0], EPS, STEPS)).withColumn("conductance", F.round("conductance", 9))


def heat_kernel(spark, sf_dir):
    return runs.heat_kernel(graph(spark, sf_dir, "line_both"), [0], terms=TERMS).withColumn("score", F.round("score", 9))


def spmv_ones(spark, sf_dir):
    return runs.spmv(graph(spark, sf_dir, "line_chain"))


def validate_bfs(spark, sf_dir):
    g = graph(spark, sf_dir, "line_chain")
    return runs.validate_bfs(g, 0, runs.bfs(g, 0))


def validate_bfs_damaged(spark, sf_dir):
    """The checks on a tree with wrong parents, wrong levels and missing vertices."""
    g = graph(spark, sf_dir, "line_chain")
    tree, vid = runs.bfs(g, 0), F.col("vid")
    wrong = F.when(vid % 11 == 1, (vid + 1) % g.n_vertices).otherwise(F.col("parent"))
    deeper = F.when(vid % 7 == 2, F.col("level") + 2).otherwise(F.col("level"))
    return runs.validate_bfs(g, 0, tree.where("vid = 0 or vid % 13 <> 3").select("vid", wrong.alias("parent"), deeper.alias("level")))


def _log(name: str, **how) -> Query:
    return lambda spark, sf_dir: runs.result_of(graph(spark, sf_dir, "line_chain"), name, **how).log_frame()


def round_log_bfs(spark, sf_dir):
    """Work of every round: what is active, sent, chosen and touched."""
    log = runs.result_of(graph(spark, sf_dir, "line_chain"), "bfs", trace=True).log_frame()
    return log.select("round", "frontier", "e_active", "msgs", "ids_sent", "sc_parts", "pc_parts", F.round("model_bytes", 6).alias("model_bytes"), "work", "touched_parts", "touched_bins")


def random_read_share(spark, sf_dir):
    g = graph(spark, sf_dir, "line_chain")
    return relational.random_read_share(g.edges, g.n_vertices)


def rmat_degree_hist(spark, sf_dir):
    """How many parts have each out-degree in the chains of the lines. It once counted a generated graph, hence the name."""
    return relational.degrees(views.g_line_chain(spark, sf_dir)).groupBy("out_deg").agg(F.count(F.lit(1)).alias("n"))


def top_rank_parts(spark, sf_dir):
    ranks = runs.pagerank(graph(spark, sf_dir, "line_chain")).withColumn("rank", F.round("rank", 9))
    return relational.top_k(ranks, "rank", 10)


def page_links(spark, sf_dir):
    return views.link_extract(table(spark, sf_dir, "pages")).groupBy("page_id").agg(F.count(F.lit(1)).alias("links"), F.count_distinct("href").alias("targets"))


def cube_events(spark, sf_dir):
    events = table(spark, sf_dir, "events").withColumn("day", F.date_trunc("day", "ts"))
    return events.cube("event_type", "day").agg(F.count(F.lit(1)).alias("n"))


def rollup_geo(spark, sf_dir):
    nation = table(spark, sf_dir, "nation").withColumnRenamed("n_nationkey", "c_nationkey")
    region = table(spark, sf_dir, "region").withColumnRenamed("r_regionkey", "n_regionkey")
    rows = table(spark, sf_dir, "customer").join(F.broadcast(nation), "c_nationkey").join(F.broadcast(region), "n_regionkey")
    return rows.rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"))


def asof_event(spark, sf_dir):
    events = table(spark, sf_dir, "events")
    bought = events.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    seen = events.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view_id"))
    return relational.asof_join(bought, seen, "user_id", "ts", ["view_id"]).select("event_id", F.coalesce("last_view_id", F.lit(-1)).alias("last_view_id"))


def interval_events(spark, sf_dir):
    events = table(spark, sf_dir, "events").withColumn("sec", F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01', ts)"))
    clicks = events.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("sec").alias("at"))
    bought = events.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("sec").alias("of"))
    return relational.interval_join(clicks, bought, ["user_id"], "at", "of", 6 * 3600 * 10**6).select("click_id", "purchase_id")


def lead_gap_events(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events").select("event_id", F.coalesce(F.lead("event_id").over(w), F.lit(-1)).alias("next_id"), F.row_number().over(w).alias("place"))


def stream_window_counts(spark, sf_dir):
    return streams.window_counts(spark, sf_dir)

def sssp_local(spark, sf_dir):
    return local.sssp_local(graph(spark, sf_dir, "line_chain"), 0)[0]


def cc_local_user_order(spark, sf_dir):
    """Chains of events under ids by user: a partition settles all but the few chains that cross."""
    n = table(spark, sf_dir, "events").count()
    return local.components_local(layout.build(views.symmetrise(views.g_event_chain(spark, sf_dir, "user")), n, K))[0]


def _cc(**how) -> Query:
    return lambda spark, sf_dir: runs.connected_components(graph(spark, sf_dir, "geo_both"), **how)


def cc_alternating_stars(spark, sf_dir):
    return utilities.alternating_stars(views.g_event_chain(spark, sf_dir))


def model_misses(spark, sf_dir):
    g = graph(spark, sf_dir, "line_chain")
    return misses.model_misses(g, cache=4 * g.q)


def triangle_count(spark, sf_dir):
    return utilities.triangles(graph(spark, sf_dir, "line_chain").edges)


def k_hop2(spark, sf_dir):
    return utilities.k_hop(graph(spark, sf_dir, "line_chain").edges, spark.range(1).withColumnRenamed("id", "vid"), 2)


def levels_histogram(spark, sf_dir):
    return utilities.levels_histogram(runs.bfs(graph(spark, sf_dir, "line_chain"), 0))


def component_sizes(spark, sf_dir):
    return utilities.component_sizes(runs.connected_components(graph(spark, sf_dir, "geo_both")))


def dangling_vertices(spark, sf_dir):
    return utilities.dangling(graph(spark, sf_dir, "geo_tree").vertices)


def degree_quantiles(spark, sf_dir):
    return utilities.quantiles(graph(spark, sf_dir, "line_chain").vertices.where("deg > 0"), "deg", [0.25, 0.5, 0.75], exact=True)


def conductance_even(spark, sf_dir):
    return utilities.conductance(graph(spark, sf_dir, "line_chain").edges, F.col("vid") % 2 == 0)


def pivot_events(spark, sf_dir):
    counts = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return utilities.pivot_grid(counts, "user_id", "event_type", "n", ["view", "signup", "error", "click", "purchase"]).fillna(0)


def _large_orders(spark, sf_dir):
    return table(spark, sf_dir, "orders").where("o_totalprice > 450000").select(F.col("o_custkey").alias("c_custkey"))


def anti_customers(spark, sf_dir):
    return relational.anti(table(spark, sf_dir, "customer").select("c_custkey"), _large_orders(spark, sf_dir))


def semi_customers(spark, sf_dir):
    return relational.semi(table(spark, sf_dir, "customer").select("c_custkey"), _large_orders(spark, sf_dir))


def _frontiers(spark, sf_dir):
    """Targets of vertex 0 and targets of vertices 1 to 20."""
    edges = graph(spark, sf_dir, "line_chain").edges
    return tuple(edges.where(F.col("src").between(*v)).select(F.col("dst").alias("vid")) for v in ((0, 0), (1, 20)))


def frontier_union(spark, sf_dir):
    return relational.union_ids(*_frontiers(spark, sf_dir))


def frontier_intersect(spark, sf_dir):
    return relational.intersect_ids(*_frontiers(spark, sf_dir))


def frontier_except(spark, sf_dir):
    return relational.except_ids(*_frontiers(spark, sf_dir))


def sampled_seeds(spark, sf_dir):
    return relational.hash_sample(graph(spark, sf_dir, "line_chain").vertices.select("vid"), "vid", 0.1)


def degree_histogram(spark, sf_dir):
    return relational.histogram(graph(spark, sf_dir, "line_chain").vertices, "deg", 5)


def grouping_sets_events(spark, sf_dir):
    events = table(spark, sf_dir, "events")
    types, users = F.col("event_type"), F.col("user_id")
    return events.groupingSets([[types], [users], []], types, users).agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("bigint").alias("level"))


def above_average_orders(spark, sf_dir):
    """Customers with an order above three halves of the mean price: a scalar subquery and EXISTS."""
    table(spark, sf_dir, "orders").createOrReplaceTempView("binflow_orders")
    table(spark, sf_dir, "customer").createOrReplaceTempView("binflow_customer")
    return spark.sql("select c_custkey from binflow_customer c where exists (select 1 from binflow_orders o where o.o_custkey = c.c_custkey and o.o_totalprice > 1.5 * (select avg(o_totalprice) from binflow_orders))")


def moving_mean_events(spark, sf_dir):
    rows = table(spark, sf_dir, "events").select("user_id", "event_id", "value")
    return relational.moving_mean(rows, ["user_id"], "event_id", "value", 4).select("event_id", F.round("mean", 6).alias("mean"))


def embed_sim_edges(spark, sf_dir):
    pairs = relational.similarity_join(table(spark, sf_dir, "embeddings").where("embedding is not null"), "vec_id", "embedding", "label", 0.3)
    return pairs.withColumn("cosine", F.round("cosine", 6))


def doc_bench_shingles(spark, sf_dir):
    return relational.shingle_join(table(spark, sf_dir, "documents"), "doc_id", table(spark, sf_dir, "benchmark"), "item_id", "text", 8)


def workload_ordering(spark, sf_dir):
    return workloads.ordering(spark, sf_dir, k=K)


def workload_mode_mix(spark, sf_dir):
    return workloads.mode_mix(spark, sf_dir, k=SMALL_K)


def workload_degree_sweep(spark, sf_dir):
    return workloads.degree_sweep(spark, k=SMALL_K)


def workload_ablation(spark, sf_dir):
    return workloads.ablation(spark, sf_dir, ("bfs", "sssp", "cc"), k=SMALL_K)


def workload_per_round(spark, sf_dir):
    return workloads.per_round(spark, sf_dir, k=SMALL_K)


def workload_shuffle_bytes(spark, sf_dir):
    return workloads.shuffle_contrast(graph(spark, sf_dir, "line_chain"))


def workload_build_time(spark, sf_dir):
    return workloads.build_time(spark, sf_dir)


def stream_sliding_counts(spark, sf_dir):
    return streams.sliding_counts(spark, sf_dir)


def stream_session_counts(spark, sf_dir):
    return streams.session_counts(spark, sf_dir)


def stream_dedup(spark, sf_dir):
    return streams.without_repeats(spark, sf_dir)


def stream_join_purchases(spark, sf_dir):
    return streams.purchases_after_clicks(spark, sf_dir)


def stream_vertex_activity(spark, sf_dir):
    return streams.vertex_activity(spark, sf_dir)


def sql_view_degrees(spark, sf_dir):
    """Out-degrees from SQL over a registered graph view."""
    views.VIEWS["part_supplier"](spark, sf_dir).createOrReplaceTempView("g_part_supplier")
    return spark.sql("select src as vid, count(*) as deg, cast(sum(weight) as bigint) as weight from g_part_supplier group by src")


def stream_incremental_cc(spark, sf_dir):
    return streams.event_components(spark, sf_dir)


def queries() -> dict[str, Query]:
    plain = (bins_summary, out_partition_degree, part_stats_r, mode_choice_all_active, mode_choice_bfs_round2, gather_list_round, bin_list_round, sssp_delta, sssp_topological, cc_geo_tree, cc_turns, pagerank_residual, nibble_line_chain, nibble_multi_seed, sweep_cut, heat_kernel, spmv_ones, validate_bfs, random_read_share, rmat_degree_hist, top_rank_parts, page_links, cube_events, rollup_geo, asof_event, interval_events, lead_gap_events, stream_window_counts)
    plain += (sssp_local, cc_local_user_order, cc_alternating_stars, model_misses, triangle_count, k_hop2, levels_histogram, component_sizes, dangling_vertices, degree_quantiles, conductance_even, pivot_events, anti_customers, semi_customers, frontier_union, frontier_intersect, frontier_except, sampled_seeds, degree_histogram, grouping_sets_events, above_average_orders, moving_mean_events, embed_sim_edges, doc_bench_shingles, validate_bfs_damaged, round_log_bfs, workload_ordering, workload_mode_mix, workload_degree_sweep, workload_ablation, workload_per_round, workload_shuffle_bytes, workload_build_time, stream_sliding_counts, stream_session_counts, stream_dedup, stream_incremental_cc, stream_join_purchases, stream_vertex_activity, sql_view_degrees)
    out: dict[str, Query] = {f.__name__: f for f in plain}
    out |= {f"interpartition_edges_{o}_order": _crossing(o) for o in ("time", "user", "hash")}
    out |= {"bfs_line_chain": _bfs(), "bfs_sc": _bfs(mode="sc"), "bfs_pc": _bfs(mode="pc"), "bfs_push": _bfs(paradigm="push"), "bfs_pull": _bfs(paradigm="pull"), "bfs_blocked": _bfs(paradigm="blocked"), "bfs_edge_centric": _bfs(paradigm="edge"), "bfs_bottom_up": _bfs_vertex("bottom_up"), "bfs_direction_opt": _bfs_vertex("auto")}
    out |= {"sssp_line_chain": _sssp(), "sssp_interleaved": _sssp(waves=2), "sssp_sc": _sssp(mode="sc"), "sssp_edge_centric": _sssp(paradigm="edge", waves=1), "sssp_push": _sssp(paradigm="push", waves=1), "sssp_pull": _sssp(paradigm="pull", waves=1), "sssp_blocked": _sssp(paradigm="blocked", waves=1)}
    out |= {"pagerank10_line_chain": _ranks("line_chain", "auto"), "pagerank10_pc": _ranks("line_chain", "pc"), "pagerank10_sc": _ranks("line_chain", "sc"),  "pagerank_pull": _ranks_by("pull"), "pagerank_push": _ranks_by("push"), "pagerank_edge_centric": _ranks_by("edge"), "pagerank_blocked": _ranks_by("blocked")}
    out |= {"cc_plain": _cc(waves=1), "cc_sc": _cc(mode="sc", waves=1), "cc_push": _cc(paradigm="push", waves=1), "cc_pull": _cc(paradigm="pull", waves=1)}
    out["cc_interleaved"] = _cc(waves=2)
    out |= {f"pagerank10_{name}": _ranks(name, "auto") for name in RANKED}
    out |= {"bfs_page_links": _bfs("page_both"), "bfs_host_links": _bfs("host_both"), "bfs_part_supplier": _bfs("part_supplier"), "bfs_copurchase": _bfs("copurchase")}
    return out | {"round_log_sssp_waves": _log("sssp", waves=4)}


RANKED = ("host_links", "page_links", "copurchase", "order_part", "event_chain")
LINE = """n as (select count(*) as n, (count(*) + 15) // 16 as q, cast(floor(log2(count(*))) as bigint) as m from part),
chain as (select l_partkey as src, lead(l_partkey) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey) as dst from lineitem),
e as (select distinct src, dst, 1 + ((31 * src + 17 * dst) % m) as weight from chain, n where dst is not null and src <> dst),
v as (select p_partkey as vid, cast(p_partkey // q as int) as part from part, n),
"""
BOTH = LINE + "b as (select src, dst from e union select dst, src from e), deg as (select src as vid, count(*) as deg from b group by src),\n"
BINS = LINE + "m as (select cast(src // q as int) as src_part, cast(dst // q as int) as dst_part, src, count(*) as ids from e, n group by all),\n"
STATS = BINS + """o as (select src, sum(ids) as deg, count(*) as opd from m group by src),
s as (select part, count(*) as n_v, cast(coalesce(sum(deg), 0) as bigint) as n_e, cast(coalesce(sum(opd), 0) as bigint) as n_msg from v left join o on vid = src group by part),
r as (select *, case when n_e > 0 then n_msg / n_e else 1.0 end as r from s),
"""
LEVELS = LINE + """walk as (select cast(0 as bigint) as vid, 0 as level union select dst, level + 1 from walk join e on src = vid where level < 12),
lev as (select vid, min(level) as level from walk group by vid),
"""
# edges of the other views over their dense ids, each as CTEs that end in e(src, dst)
HREFS = "l as (select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host from pages), t as (select href, row_number() over (order by href) - 1 as h from (select distinct href from l)),\n"
EDGES = {
    "page_links": HREFS + "e as (select distinct page_id as src, h + (select count(*) from pages) as dst from l join t using (href)),",
    "host_links": HREFS + "s as (select host, row_number() over (order by host) - 1 as i from (select distinct regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host from pages)), e as (select distinct i as src, h + (select count(*) from s) as dst from l join t using (href) join s using (host)),",
    "copurchase": "e as (select distinct a.l_partkey as src, b.l_partkey as dst from lineitem a join lineitem b using (l_orderkey) where a.l_partkey <> b.l_partkey),",
    "order_part": "h as (select distinct l_orderkey as src, l_partkey + (select count(*) from orders) as dst from lineitem), e as (select src, dst from h union select dst, src from h),",
    "part_supplier": "h as (select distinct l_partkey as src, l_suppkey + (select count(*) from part) as dst from lineitem), e as (select src, dst from h union select dst, src from h),",
    "event_chain": "c as (select event_id as src, lead(event_id) over (partition by user_id order by ts, event_id) as dst from events), e as (select src, dst from c where dst is not null),",
}
SIZES = {"copurchase": "select count(*) as n from part", "event_chain": "select count(*) as n from events"}


def _rank_sql(name: str) -> str:
    """Ten unrolled rounds over a view; its vertices are 0 to the largest id unless a table counts them."""
    head = f"{EDGES[name]} n as ({SIZES.get(name, 'select 1 + max(greatest(src, dst)) as n from e')}), v as (select unnest(range(n)) as vid from n), d as (select src as vid, count(*) as deg from e group by src),"
    step = "select v.vid, 0.15 / n + 0.85 * coalesce(t, 0) as x from n, v left join (select dst, sum(x / deg) as t from {s} join e on src = vid join d using (vid) group by dst) on dst = v.vid"
    return _steps("select vid, 1.0::double / n as x from v, n", step, 10, "select vid, round(x, 9) as rank from {s}", head)


def _bfs_sql(edges: str) -> str:
    """Levels by recursion over distinct (vertex, level), then the smallest parent one level up."""
    return f"""with recursive {edges} walk as (select cast(0 as bigint) as vid, 0 as level union select dst, level + 1 from walk join e on src = vid where level < 24),
    lev as (select vid, min(level) as level from walk group by vid),
    par as (select b.vid, min(a.vid) as parent from lev b join e on dst = b.vid join lev a on a.vid = src and a.level = b.level - 1 group by b.vid)
    select lev.vid, coalesce(parent, lev.vid) as parent, lev.level from lev left join par using (vid)"""


def _both(edges: str) -> str:
    """The same edges in both directions."""
    return re.sub(r"\be as \(", "f as (", edges) + " e as (select src, dst from f union select dst, src from f),"


def _checks_sql(damage: bool) -> str:
    """The four checks of a BFS tree, on the tree as found or with the damage of ``validate_bfs_damaged``."""
    tree = "select vid, case when vid % 11 = 1 then (vid + 1) % n else parent end as parent, case when vid % 7 = 2 then level + 2 else level end as level from found, n where vid = 0 or vid % 13 <> 3" if damage else "select * from found"
    return f"""with {LINE} found as ({BFS}), tree as ({tree}), child as (select * from tree where vid <> 0),
    both_ as (select a.level as ls, b.level as ld from e join tree a on a.vid = src left join tree b on b.vid = dst)
    select 'parent edge exists' as "check", count(*) as failures from child where not exists (select 1 from e where src = parent and dst = child.vid)
    union all select 'level is the parent''s plus one', count(*) from child left join tree up on up.vid = child.parent where up.level is null or up.level <> child.level - 1
    union all select 'no edge spans two levels', count(*) from both_ where ld > ls + 1
    union all select 'reach is closed', count(*) from both_ where ld is null"""


def _log_sql() -> str:
    """Work of the BFS rounds from the levels: the frontier of round r are the vertices of level r - 1."""
    return f"""with recursive {LEVELS.replace(LINE, STATS)}
    w as (select level + 1 as round, part, count(*) as v_a, sum(coalesce(deg, 0)) as e_a, sum(coalesce(opd, 0)) as m_a from lev join v using (vid) left join o on vid = src group by level, part),
    c as (select w.*, n_e, n_msg, (v_a + e_a) * 4 + 2 * (r.r * e_a * 4 + e_a * 4) as sc, n_e * ((r.r + 1) * 4 + 8 * r.r) + 16 * 4 as pc from w join r using (part)),
    p as (select *, pc / 2 <= sc as is_pc from c),
    hit as (select distinct p.round, src_part, dst_part from p join lev on level + 1 = p.round join v using (vid) join m on src = vid and src_part = p.part where v.part = p.part),
    t as (select round, count(distinct dst_part) as touched_parts, count(*) as touched_bins from hit group by round)
    select p.round, cast(sum(v_a) as bigint) as frontier, cast(sum(e_a) as bigint) as e_active, cast(sum(case when is_pc then n_msg else m_a end) as bigint) as msgs, cast(sum(case when is_pc then 0 else e_a end) as bigint) as ids_sent,
    cast(sum((not is_pc)::int) as int) as sc_parts, cast(sum(is_pc::int) as int) as pc_parts, round(cast(sum(case when is_pc then pc / 2 else sc end) as double), 6) as model_bytes,
    cast(sum(case when is_pc then n_msg + n_e else m_a + e_a end) as bigint) as work, cast(any_value(touched_parts) as int) as touched_parts, any_value(touched_bins) as touched_bins
    from p join t using (round) group by p.round"""


def _heat_sql() -> str:
    """Walk powers, weighed and summed."""
    step = "select dst as vid, sum(p / deg) as p from {s} join deg using (vid) join b on src = vid group by dst"
    weights = [math.exp(-5.0) * 5.0**j / math.factorial(j) for j in range(TERMS + 1)]
    parts = [f"s{j + 1} as materialized ({step.format(s=f's{j}')})" for j in range(TERMS)]
    total = " union all ".join(f"select vid, p * {w!r}::double as score from s{j}" for j, w in enumerate(weights))
    return f"with {BOTH} s0 as (select cast(0 as bigint) as vid, 1.0::double as p), {', '.join(parts)} select cast(0 as bigint) as seed, vid, round(sum(score), 9) as score from ({total}) group by vid"


def _sweep_sql() -> str:
    """Prefixes of the walk, with the edges that close when a vertex joins."""
    walk = _nibble_sql("(0)").replace("round(p, 9) as p", "p")
    return f"""with {BOTH} walk as ({walk}), total as (select count(*) as total from b),
    ranked as (select walk.vid, deg, row_number() over (order by p / deg desc, walk.vid) as k from walk join deg using (vid) where p > 0),
    closing as (select x.vid, count(*) as c from ranked x join b on src = x.vid join ranked y on y.vid = dst where y.k < x.k group by x.vid),
    sums as (select k, vid, sum(deg) over (order by k) as volume, sum(deg - 2 * coalesce(c, 0)) over (order by k) as cut from ranked left join closing using (vid))
    select cast(0 as bigint) as seed, cast(k as int) as k, vid, round(cut / least(volume, total - volume), 9) as conductance from sums, total where volume < total"""


BFS = f"""with recursive {LEVELS} par as (select b.vid, min(a.vid) as parent from lev b join e on dst = b.vid join lev a on a.vid = src and a.level = b.level - 1 group by b.vid)
select lev.vid, coalesce(parent, lev.vid) as parent, lev.level from lev left join par using (vid)"""


def _steps(first: str, step: str, n: int, last: str, head: str) -> str:
    parts = [f"s0 as materialized ({first})", *(f"s{i + 1} as materialized ({step.format(s=f's{i}')})" for i in range(n))]
    return f"with {head} {', '.join(parts)} {last.format(s=f's{n}')}"


def _mode_sql(active: str) -> str:
    return f"""with {STATS} act as ({active}),
w as (select part, count(*) as v_a, cast(sum(coalesce(deg, 0)) as bigint) as e_a from act join v using (vid) left join o on vid = src group by part),
c as (select part, v_a, e_a, (v_a + e_a) * 4 + 2 * (r.r * e_a * 4 + e_a * 4) as cost_sc, n_e * ((r.r + 1) * 4 + 8 * r.r) + 16 * 4 as cost_pc from w join r using (part))
select part, v_a, e_a, round(cast(cost_sc as double), 6) as cost_sc, round(cast(cost_pc as double), 6) as cost_pc, case when cost_pc / 2 <= cost_sc then 'pc' else 'sc' end as mode from c"""


def _nibble_sql(seeds: str) -> str:
    step = f"""select x.seed, x.vid, sum(x.p) as p, (bool_or(got) or bool_or(stay)) and sum(x.p) >= {EPS} * any_value(deg.deg) as active, any_value(deg.deg) as deg from (
select seed, vid, case when active then p / 2 else p end as p, false as got, active and p / 2 >= {EPS} * deg as stay from {{s}}
union all select seed, dst, p / (2 * deg), true, false from {{s}} join b on src = vid where active) x join deg on deg.vid = x.vid group by x.seed, x.vid"""
    first = f"select cast(seed as bigint) as seed, cast(seed as bigint) as vid, 1.0::double as p, true as active, deg from (values {seeds}) t(seed) join deg on deg.vid = seed"
    return _steps(first, step, STEPS, "select seed, vid, round(p, 9) as p from {s}", BOTH.rstrip("\n"))


def oracle_sql() -> dict[str, str]:
    ranks = _steps("select vid, 1.0::double / n as x from v, n", "select v.vid, 0.15 / n + 0.85 * coalesce(t, 0) as x from n, v left join (select dst, sum(x / deg) as t from {s} join e on src = vid join (select src as vid, count(*) as deg from e group by src) using (vid) group by dst) on dst = v.vid", 10, "select vid, round(x, 9) as rank from {s}", LINE.rstrip("\n"))
    paths = _steps("select cast(0 as bigint) as vid, cast(0 as bigint) as dist", "select vid, min(dist) as dist from (select * from {s} union all select dst, dist + weight from {s} join e on src = vid) group by vid", 16, "select vid, cast(dist as bigint) as dist from {s}", LINE.rstrip("\n"))
    front = "select distinct dst as vid from e where src = 0"
    crossing = "select count(*) as edges, cast(sum((a // q <> b // q)::int) as bigint) as crossing, round(sum((a // q <> b // q)::int) / count(*), 9) as share from c, n"
    out = {
        "bins_summary": f"with {BINS.rstrip().rstrip(',')} select src_part, dst_part, count(*) as msgs, cast(sum(ids) as bigint) as ids from m group by all",
        "out_partition_degree": f"with {BINS.rstrip().rstrip(',')} select src, cast(sum(ids) as bigint) as deg, count(*) as opd from m group by src",
        "part_stats_r": f"with {STATS.rstrip().rstrip(',')} select part, n_v, n_e, n_msg, round(r, 9) as r from r",
        "mode_choice_all_active": _mode_sql("select vid from v"),
        "mode_choice_bfs_round2": _mode_sql(front),
        "gather_list_round": f"with {BINS} f as ({front}) select distinct dst_part from m join f on vid = src",
        "bin_list_round": f"with {BINS} f as ({front}) select distinct dst_part, src_part from m join f on vid = src",
        "interpartition_edges_time_order": f"with n as (select (count(*) + 15) // 16 as q from events), c as (select event_id as a, lead(event_id) over (partition by user_id order by ts, event_id) as b from events qualify b is not null) {crossing}",
        "interpartition_edges_user_order": f"with n as (select (count(*) + 15) // 16 as q from events), i as (select event_id, user_id, ts, row_number() over (order by user_id, ts, event_id) - 1 as vid from events), c as (select vid as a, lead(vid) over (partition by user_id order by ts, event_id) as b from i qualify b is not null) {crossing}",
        "cc_geo_tree": """with s as (select (select count(*) from region) as r, (select count(*) from nation) as n, (select count(*) from customer) as c, (select count(*) from supplier) as u)
            select cast(r_regionkey as bigint) as vid, cast(r_regionkey as bigint) as label from region
            union all select n_nationkey + r, n_regionkey from nation, s
            union all select c_custkey + r + n, n_regionkey from customer join nation on c_nationkey = n_nationkey, s
            union all select s_suppkey + r + n + c, n_regionkey from supplier join nation on s_nationkey = n_nationkey, s
            union all select o_orderkey + r + n + c + u, n_regionkey from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey, s""",
        "cc_turns": "select 8 * conv_id + turn as vid, min(8 * conv_id + turn) over (partition by conv_id) as label from conversations",
        "nibble_line_chain": _nibble_sql("(0)"),
        "nibble_multi_seed": _nibble_sql("(0), (1), (2)"),
        "spmv_ones": f"with {LINE.rstrip().rstrip(',')} select vid, cast(coalesce(sum(weight), 0) as double) as y from v left join e on dst = vid group by vid",
        "random_read_share": f"with {LINE} c as (select count(*) as m from e) select round(m * 64 / (m * 64 + m * 4 + n * 8), 9) as share from c, n",
        "validate_bfs": _checks_sql(False),
        "validate_bfs_damaged": _checks_sql(True),
        "round_log_bfs": _log_sql(),
        "rmat_degree_hist": f"with {LINE} o as (select src as vid, count(*) as out_deg from e group by src), i as (select distinct dst as vid from e) select coalesce(out_deg, 0) as out_deg, count(*) as n from o full join i using (vid) group by 1",
        "heat_kernel": _heat_sql(),
        "sweep_cut": _sweep_sql(),
        "anti_customers": "select c_custkey from customer where c_custkey not in (select o_custkey from orders where o_totalprice > 450000)",
        "semi_customers": "select c_custkey from customer where c_custkey in (select o_custkey from orders where o_totalprice > 450000)",
        "frontier_union": f"with {LINE} z as (select 1) select dst as vid from e where src = 0 union select dst from e where src between 1 and 20",
        "frontier_intersect": f"with {LINE} z as (select 1) select dst as vid from e where src = 0 intersect select dst from e where src between 1 and 20",
        "frontier_except": f"with {LINE} z as (select 1) select dst as vid from e where src = 0 except select dst from e where src between 1 and 20",
        "sampled_seeds": "select p_partkey as vid from part where (p_partkey % 65521 * 40503 + 12289) % 65536 < 6553",
        "degree_histogram": f"with {LINE} d as (select vid, count(src) as deg from v left join e on src = vid group by vid) select deg // 5 * 5 as low, count(*) as n from d group by 1",
        "grouping_sets_events": "select event_type, user_id, count(*) as n, cast(grouping(event_type, user_id) as bigint) as level from events group by grouping sets ((event_type), (user_id), ())",
        "above_average_orders": "select c_custkey from customer where c_custkey in (select o_custkey from orders where o_totalprice > 1.5 * (select avg(o_totalprice) from orders))",
        "moving_mean_events": "select event_id, round(avg(value) over (partition by user_id order by event_id rows between 4 preceding and current row), 6) as mean from events",
        "embed_sim_edges": "with v as (select vec_id, label, list_transform(embedding, lambda x: x::double) as e from embeddings), c as (select x.vec_id as a, y.vec_id as b, list_cosine_similarity(x.e, y.e) as cosine from v x join v y on x.label = y.label and x.vec_id < y.vec_id) select a, b, round(cosine, 6) as cosine from c where cosine >= 0.3",
        "doc_bench_shingles": """with w as (select 0 as side, doc_id as id, list_filter(regexp_split_to_array(lower(text), '[ \\t\\r\\n]+'), lambda x: x <> '') as w from documents union all select 1, item_id, list_filter(regexp_split_to_array(lower(text), '[ \\t\\r\\n]+'), lambda x: x <> '') from benchmark),
            s as (select distinct side, id, array_to_string(w[i:i + 7], ' ') as shingle from (select side, id, w, unnest(range(1, len(w) - 6)) as i from w))
            select x.id as a, y.id as b, count(*) as shared from s x join s y using (shingle) where x.side = 0 and y.side = 1 group by all""",
        "top_rank_parts": f"select * from ({ranks}) order by rank desc, vid limit 10",
        "page_links": "with l as (select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href from pages) select page_id, count(*) as links, count(distinct href) as targets from l group by page_id",
        "cube_events": "select event_type, date_trunc('day', ts)::timestamp as day, count(*) as n from events group by cube (event_type, day)",
        "rollup_geo": "select r_name, n_name, count(*) as customers from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)",
        "asof_event": "select b.event_id, coalesce(a.event_id, -1) as last_view_id from (select * from events where event_type = 'purchase') b asof left join (select * from events where event_type = 'view') a on a.user_id = b.user_id and a.ts <= b.ts",
        "interval_events": "select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and p.ts >= c.ts and p.ts < c.ts + interval 6 hour where c.event_type = 'click' and p.event_type = 'purchase'",
        "lead_gap_events": "select event_id, coalesce(lead(event_id) over w, -1) as next_id, cast(row_number() over w as int) as place from events window w as (partition by user_id order by ts, event_id)",
        "stream_window_counts": "select date_trunc('day', ts)::timestamp as day, event_type, count(*) as n from events group by all",
    }
    out |= {
        "interpartition_edges_hash_order": f"with n as (select (count(*) + 15) // 16 as q from events), i as (select event_id, user_id, ts, row_number() over (order by (event_id * 2654435761) % 4294967296, event_id) - 1 as vid from events), c as (select vid as a, lead(vid) over (partition by user_id order by ts, event_id) as b from i qualify b is not null) {crossing}",
        "cc_local_user_order": "with i as (select user_id, row_number() over (order by user_id, ts, event_id) - 1 as vid from events) select vid, min(vid) over (partition by user_id) as label from i",
        "cc_alternating_stars": "select event_id as vid, min(event_id) over (partition by user_id) as label from events qualify count(*) over (partition by user_id) > 1",
        "model_misses": f"""with {BINS} t as (select sum(ids) as e, count(*) as m from m), a as (select count(distinct src * 4 // 64) as a from e), b as (select count(distinct dst * 4 // 64) as b from e),
            h as (select t.e, t.m, a, b, least(1.0, 4.0 * q / (4 * n)) as held from t, a, b, n)
            select 'sc' as paradigm, round(cast(a + b + (8 * m + 12 * e) / 64 as double), 6) as misses from h union all select 'pc', round(cast(a + b + (8 * m + 4 * (m + e)) / 64 as double), 6) from h
            union all select 'push', round(cast(b + greatest(e - b, 0) * (1 - held) + e * 4 / 64 as double), 6) from h union all select 'pull', round(cast(a + greatest(e - a, 0) * (1 - held) + e * 4 / 64 as double), 6) from h""",
        "triangle_count": f"with {LINE} p as (select distinct least(src, dst) as a, greatest(src, dst) as b from e) select count(*) as triangles from p x join p y on x.b = y.a join p z on z.a = x.a and z.b = y.b",
        "k_hop2": f"with recursive {LEVELS} z as (select 1) select vid, level as hops from lev where level <= 2",
        "levels_histogram": f"with recursive {LEVELS} z as (select 1) select level, count(*) as n from lev group by level",
        "component_sizes": f"select label, count(*) as n from ({out['cc_geo_tree']}) group by label",
        "dangling_vertices": """with s as (select (select count(*) from region) as r, (select count(*) from nation) as n, (select count(*) from customer) as c, (select count(*) from supplier) as u)
            select o_orderkey + r + n + c + u as vid from orders, s union all select s_suppkey + r + n + c from supplier, s
            union all select c_custkey + r + n from customer, s where c_custkey not in (select o_custkey from orders)
            union all select n_nationkey + r from nation, s where n_nationkey not in (select c_nationkey from customer) and n_nationkey not in (select s_nationkey from supplier)
            union all select r_regionkey from region where r_regionkey not in (select n_regionkey from nation)""",
        "degree_quantiles": f"with {LINE} d as (select count(*) as deg from e group by src) select unnest([0.25, 0.5, 0.75])::double as share, unnest(quantile_cont(deg, [0.25, 0.5, 0.75]))::double as value from d",
        "conductance_even": f"with {LINE} s as (select cast(count(*) filter (where src % 2 = 0 and dst % 2 = 1) as bigint) as cut, count(*) filter (where src % 2 = 0) as volume, count(*) as total from e) select cut, volume, round(cut / least(volume, total - volume), 9) as conductance from s",
        "pivot_events": "select user_id, " + ", ".join(f"count(*) filter (where event_type = '{t}') as \"{t}\"" for t in ("view", "signup", "error", "click", "purchase")) + " from events group by user_id",
        "stream_sliding_counts": "select (time_bucket(interval 6 hour, ts) - to_hours(6 * i))::timestamp as start, event_type, count(*) as n from events, range(4) r(i) group by all",
        "stream_session_counts": """with g as (select user_id, ts, coalesce(ts - lag(ts) over (partition by user_id order by ts) >= interval 2 hour, true)::int as new from events),
            s as (select user_id, ts, sum(new) over (partition by user_id order by ts) as s from g) select user_id, min(ts)::timestamp as start, count(*) as n from s group by user_id, s""",
        "stream_dedup": "select event_id, event_type from events",
    }
    orders = {o: out[f"interpartition_edges_{o}_order"].replace("select count(*) as edges", f"select '{o}' as id_order, count(distinct (a, b // q)) as msgs, count(*) as edges") for o in ("user", "time", "hash")}
    out["workload_ordering"] = " union all ".join(f"select * from ({q})" for q in orders.values())
    out |= {f"pagerank10_{name}": _rank_sql(name) for name in RANKED}
    out |= {"bfs_page_links": _bfs_sql(_both(EDGES["page_links"])), "bfs_host_links": _bfs_sql(_both(EDGES["host_links"])), "bfs_part_supplier": _bfs_sql(EDGES["part_supplier"]), "bfs_copurchase": _bfs_sql(EDGES["copurchase"])}
    out["stream_join_purchases"] = out["interval_events"]
    out["stream_vertex_activity"] = "select user_id, count(*) as n, max(epoch_us(ts)) as last_us from events group by user_id"
    out["sql_view_degrees"] = "with h as (select l_partkey as a, l_suppkey + (select count(*) from part) as b, count(*) as w from lineitem group by all), e as (select a, b, w from h union all select b, a, w from h) select a as vid, count(*) as deg, cast(sum(w) as bigint) as weight from e group by a"
    out["stream_incremental_cc"] = out["cc_alternating_stars"]
    out |= dict.fromkeys(("cc_plain", "cc_sc", "cc_push", "cc_pull", "cc_interleaved"), out["cc_geo_tree"])
    out |= dict.fromkeys(("bfs_pull", "bfs_blocked", "bfs_line_chain", "bfs_sc", "bfs_pc", "bfs_push", "bfs_edge_centric", "bfs_bottom_up", "bfs_direction_opt"), BFS)
    out |= dict.fromkeys(("sssp_local", "sssp_edge_centric", "sssp_line_chain", "sssp_interleaved", "sssp_sc", "sssp_push", "sssp_pull", "sssp_blocked", "sssp_delta", "sssp_topological"), paths)
    return out | dict.fromkeys(("pagerank10_line_chain", "pagerank10_sc", "pagerank10_pc", "pagerank_push", "pagerank_pull", "pagerank_edge_centric", "pagerank_blocked"), ranks)
