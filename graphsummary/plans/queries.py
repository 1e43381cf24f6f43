"""One registered query for each method, variant, baseline, measure and operator, over the given tables.

Unless it says otherwise a query runs on the planted graph: customer-part pairs with 15 known groups.
"""

from __future__ import annotations

from collections.abc import Callable
from contextvars import ContextVar

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphsummary.functions.register import register
from graphsummary.operators import baselines, detect, draw, edges, hierarchy, layout, measure, rounds, sketch, summary
from graphsummary.params import Params
from graphsummary.plans import case, pipeline
from graphsummary.sources import catalogue as g
from graphsummary.sources import readers
from graphsummary.operators.order import numbered
from graphsummary.sources.storage import shared_dir, store
from graphsummary.streaming import attach, windows

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
CAP = 3
WIDTH = 257


def query(f: Callable[[SparkSession, str], DataFrame]):
    QUERIES[f.__name__] = f
    return f


def named(name: str, f: Callable[[SparkSession, str], DataFrame]) -> None:
    QUERIES[name] = f


def rounded(c: str, digits: int = 6) -> Column:
    return (F.round(c, digits) + F.lit(0.0)).alias(c)


#: The graph that planted() gives; whole() sets another one while it builds a query.
_GRAPH = ContextVar("graph", default="planted")


def planted(s: SparkSession, d: str) -> DataFrame:
    return g.graph(s, d, _GRAPH.get())


def whole(name: str, graph: str) -> None:
    """Register a query on a whole graph too, as name_graph; it has no SQL."""

    def run(s, d, f=QUERIES[name]):
        token = _GRAPH.set(graph)
        try:
            return f(s, d)
        finally:
            _GRAPH.reset(token)

    QUERIES[f"{name}_{graph}"] = run


def sized(s: SparkSession, d: str) -> DataFrame:
    """(community, size, n_nodes) of the planted groups."""
    e = planted(s, d)
    return summary.exact_sizes(g.planted_truth(e), edges.degrees(e))


def placed(s: SparkSession, d: str) -> DataFrame:
    """The start layout of the planted groups' supergraph, mass by size."""
    return layout.init(sized(s, d).select(F.col("community").alias("node"), "size"), mass="size")


def group_edges(s: SparkSession, d: str) -> DataFrame:
    e = planted(s, d)
    return summary.superedges(e, g.planted_truth(e))


# ---------------------------------------------------------------- edges
@query
def canonical_edges(s, d):
    return edges.canonical(g.user_next_rows(s, d), repeats="sum").select("src", "dst", "w")


@query
def arrival_rank(s, d):
    return planted(s, d).select("seq", "src", "dst")


@query
def degrees(s, d):
    return edges.degrees(planted(s, d))


@query
def degrees_directed(s, d):
    return edges.directed_degrees(g.nation_trade(s, d))


@query
def degrees_weighted(s, d):
    return edges.degrees(edges.canonical(g.nation_trade(s, d), weight="w", loops="keep", repeats="sum"), weighted=True)


@query
def degree_histogram(s, d):
    return edges.degree_histogram(edges.degrees(planted(s, d)))


named("base_cap_mode", lambda s, d: edges.cap_frame(planted(s, d), "mode"))
named("base_cap_average", lambda s, d: edges.cap_frame(planted(s, d), "average"))


# ---------------------------------------------------------------- detection
@query
def admitted_edges(s, d):
    return detect.admitted(planted(s, d), CAP)


@query
def copy_events(s, d):
    return detect.copy_events(detect.admitted(planted(s, d), CAP))


@query
def event_pointers(s, d):
    return detect.event_pointers(detect.copy_events(detect.admitted(planted(s, d), CAP)))


for _name, _admit, _tie in (("le_source", "le", "source"), ("le_hold", "le", "hold"), ("lt_source", "lt", "source"), ("lower_id", "le", "lower_id")):
    named(f"assignment_{_name}", lambda s, d, a=_admit, t=_tie: detect.stream(planted(s, d), CAP, a, t))


@query
def assignment(s, d):
    return detect.stream(g.graph(s, d, "order_part"), 4)


@query
def assignment_two_rounds(s, d):
    return rounds.detect(store(planted(s, d), "edges"), cap_list=[2, 4]).assignment


@query
def assignment_labels_carried(s, d):
    return rounds.detect(store(planted(s, d), "edges"), cap_list=[2, 4], carry="labels").assignment


@query
def bulk_assignment(s, d):
    return detect.bulk(planted(s, d), CAP)


@query
def sliced_assignment(s, d):
    return detect.stream_sliced(planted(s, d), CAP, 8)


@query
def loop_assignment(s, d):
    return detect.stream_loop(planted(s, d), CAP)


named("loop_admitted", lambda s, d: detect.stream_loop(planted(s, d), CAP, count="admitted"))
named("loop_stalled", lambda s, d: detect.stream_loop(planted(s, d), CAP, count="joiner", tie="hold"))


@query
def multi_round(s, d):
    return rounds.metrics_frame(s, rounds.detect(store(planted(s, d), "edges"), with_q=True).metrics)


@query
def hierarchy_paths(s, d):
    return hierarchy.path(rounds.detect(store(planted(s, d), "edges"), cap_list=[2, 4]).hierarchy)


@query
def members(s, d):
    e = store(planted(s, d), "edges")
    h = rounds.detect(e, cap_list=[2, 4])
    top = h.assignment.groupBy("community").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "community").first()[0]
    return hierarchy.members(h.hierarchy, top, 2)


# ---------------------------------------------------------------- sketch and sizes
@query
def community_sizes_exact(s, d):
    return sized(s, d)


@query
def sketch_cells(s, d):
    return sketch.build(edges.degrees(planted(s, d)), "node", "deg", 4, WIDTH)


for _depth in (1, 2, 3, 4):
    named(f"sketch_estimate_d{_depth}", lambda s, d, k=_depth: sketch.estimate(sketch.build(edges.degrees(planted(s, d)), "node", "deg", k, WIDTH), edges.degrees(planted(s, d)), "node", k, WIDTH))


@query
def sketch_sizes(s, d):
    e = planted(s, d)
    return summary.sizes(g.planted_truth(e), edges.degrees(e), "sketch", width=WIDTH)


@query
def sketch_error(s, d):
    deg = store(edges.degrees(planted(s, d)), "degrees")
    est = sketch.estimate(sketch.build(deg, "node", "deg", 4, WIDTH), deg, "node", 4, WIDTH)
    return measure.sketch_error(est, deg).select(*[rounded(c) if c in ("mean_error", "p95_error") else F.col(c) for c in ("mean_error", "max_error", "min_error", "p95_error")])


@query
def sketch_column_min(s, d):
    return sketch.column_min(sketch.build(edges.degrees(planted(s, d)), "node", "deg", 4, WIDTH), 4)


@query
def sketch_merge(s, d):
    deg = edges.degrees(planted(s, d))
    low = F.col("node") < g.SECOND
    return sketch.merge(sketch.build(deg.where(low), "node", "deg", 4, WIDTH), sketch.build(deg.where(~low), "node", "deg", 4, WIDTH))


@query
def sketch_sequential(s, d):
    return sketch.sketch_loop(edges.degrees(planted(s, d)), "node", "deg", 4, WIDTH)


@query
def hash_table_sizes(s, d):
    e = planted(s, d)
    return baselines.hash_table_sizes(g.planted_truth(e), edges.degrees(e), 17)


@query
def supernodes(s, d):
    e = planted(s, d)
    a = g.planted_truth(e)
    return summary.supergraph(e, a, sized(s, d).select("community", "size"))[0]


@query
def superedges(s, d):
    return group_edges(s, d)


@query
def supergraph_counts(s, d):
    e = store(planted(s, d), "edges")
    a = store(detect.stream(e, CAP), "labels")
    return measure.counts(a.select("community").distinct(), summary.superedges(e, a))


@query
def compression(s, d):
    e = store(planted(s, d), "edges")
    a = store(detect.stream(e, CAP), "labels")
    c = measure.counts(a.select("community").distinct(), summary.superedges(e, a))
    return measure.compression(a, e, c).select(rounded("node_ratio"), rounded("edge_ratio"))


# ---------------------------------------------------------------- measures
@query
def edge_split(s, d):
    e = planted(s, d)
    return measure.edge_split(e, g.planted_truth(e))


@query
def modularity(s, d):
    e = planted(s, d)
    return measure.modularity(e, g.planted_truth(e)).select(rounded("q"))


@query
def modularity_found(s, d):
    e = store(planted(s, d), "edges")
    return measure.modularity(e, detect.stream(e, CAP)).select(rounded("q"))


@query
def modularity_pairs(s, d):
    e = store(planted(s, d), "edges")
    return measure.modularity_pairs(e, g.planted_truth(e)).select(rounded("q"))


@query
def modularity_weighted(s, d):
    e = edges.canonical(g.nation_trade(s, d), weight="w", loops="keep", repeats="sum")
    a = g.table(s, d, "nation").select(F.col("n_nationkey").cast("bigint").alias("node"), F.col("n_regionkey").cast("bigint").alias("community"))
    return measure.modularity(e, a, weight=True).select(rounded("q"))


@query
def intra_probability(s, d):
    e = planted(s, d)
    return measure.intra_probability(measure.edge_split(e, g.planted_truth(e)), 5).select("community", rounded("p"))


@query
def phi(s, d):
    e = planted(s, d)
    return measure.phi(measure.edge_split(e, g.planted_truth(e)), 2).select("community", rounded("phi"))


def _found(s, d):
    e = store(planted(s, d), "edges")
    return store(detect.stream(e, CAP), "labels"), g.planted_truth(e)


named("purity", lambda s, d: measure.purity(*_found(s, d)).select(rounded("purity")))
named("nmi", lambda s, d: measure.nmi(*_found(s, d)).select(rounded("nmi")))
named("pair_scores", lambda s, d: measure.pair_scores(*_found(s, d)).select(rounded("pair_precision"), rounded("pair_recall"), rounded("pair_f1")))


@query
def assignment_agreement(s, d):
    e = store(planted(s, d), "edges")
    return measure.agreement(detect.stream(e, CAP), detect.stream(e, CAP, tie="hold"))


@query
def size_profile(s, d):
    e = store(planted(s, d), "edges")
    return measure.size_profile(summary.exact_sizes(detect.stream(e, CAP), edges.degrees(e)))


@query
def large_blobs(s, d):
    return measure.large_blobs(sized(s, d), 0.05)


@query
def sketch_memory(s, d):
    n = edges.degrees(planted(s, d)).agg((F.lit(4 * WIDTH)).cast("bigint").alias("cells"), F.lit(4 * WIDTH * 8).cast("bigint").alias("bytes"), (F.sum("deg") / WIDTH).alias("load"))
    return n.select("cells", "bytes", rounded("load"))


# ---------------------------------------------------------------- layout, one step
def _step(s, d):
    at = placed(s, d)
    return layout.add_forces(at, layout.gravity(at), layout.attraction(at, group_edges(s, d)), layout.repulsion_exact(at))


_xy = lambda df, *c: df.select("node", *[rounded(x, 3) for x in c])
named("layout_init", lambda s, d: _xy(placed(s, d), "x", "y", "mass"))
named("gravity_step", lambda s, d: _xy(layout.gravity(placed(s, d)), "fx", "fy"))
named("gravity_strong_step", lambda s, d: _xy(layout.gravity(placed(s, d), mode="strong"), "fx", "fy"))
named("attraction_step", lambda s, d: _xy(layout.attraction(placed(s, d), group_edges(s, d)), "fx", "fy"))
named("attraction_unit_step", lambda s, d: _xy(layout.attraction(placed(s, d), group_edges(s, d), "unit"), "fx", "fy"))
named("attraction_log_step", lambda s, d: _xy(layout.attraction(placed(s, d), group_edges(s, d), "log"), "fx", "fy"))
named("repulsion_exact_step", lambda s, d: _xy(layout.repulsion_exact(placed(s, d).withColumn("mass", F.lit(1.0))), "fx", "fy"))
named("repulsion_weighted_step", lambda s, d: _xy(layout.repulsion_exact(placed(s, d)), "fx", "fy"))
named("repulsion_tree_step", lambda s, d: _xy(layout.repulsion_tree(layout.init(edges.nodes(planted(s, d)))), "fx", "fy"))
named("repulsion_opened_step", lambda s, d: _xy(layout.repulsion_opened(layout.init(edges.nodes(planted(s, d)))), "fx", "fy"))
named("repulsion_opened_exact", lambda s, d: _xy(layout.repulsion_opened(placed(s, d), theta=0.0, leaf=1), "fx", "fy"))
named("speeds_step", lambda s, d: layout.speeds(_step(s, d)).select("node", rounded("swing", 3), rounded("speed", 6)))
named("speeds_paper_step", lambda s, d: layout.speeds(_step(s, d), rule="paper").select("node", rounded("swing", 3), rounded("speed", 6)))


@query
def move_step(s, d):
    f = _step(s, d)
    return _xy(layout.move(f, layout.speeds(f)), "x", "y")


@query
def extent(s, d):
    e = planted(s, d)
    return measure.extent(layout.init(edges.nodes(e)), g.planted_truth(e), 10.0).select("community", "n_nodes", rounded("rms_radius"), "cells")


@query
def scatter(s, d):
    e = planted(s, d)
    return measure.scatter(layout.init(edges.nodes(e)), g.planted_truth(e)).select("community", rounded("scatter"))


@query
def rank_corr(s, d):
    return measure.rank_corr(sized(s, d), "size", "n_nodes").select(rounded("rho"))


#: Steps of the planted groups' layout that are traced, and the shares of the diameter that count as still.
TRACED, STILL = 4, (0.01, 0.1, 0.2)


@query
def stable_iteration(s, d):
    """When the layout of the planted groups' supergraph stops moving, for each share of the diameter."""
    nodes = sized(s, d).select(F.col("community").alias("node"), "size")
    trace, out = layout.run(nodes, group_edges(s, d), TRACED, mass="size")[1], None
    for eps in STILL:
        row = measure.stable_iteration(trace, eps).select(F.lit(eps).alias("eps"), "stable")
        out = row if out is None else out.unionByName(row)
    return out


# ---------------------------------------------------------------- drawing
@query
def radius(s, d):
    return draw.radius(sized(s, d)).select("community", rounded("radius"))


def _many(s, d):
    e = store(planted(s, d), "edges")
    return summary.exact_sizes(detect.stream(e, CAP), edges.degrees(e))


named("colour_bands", lambda s, d: draw.qualitative(_many(s, d)).select("community", "size", "band", "name"))
named("colour_bands_weight", lambda s, d: draw.qualitative(_many(s, d), bands="equal_weight").select("community", "size", "band", "name"))
named("colour_bands_log", lambda s, d: draw.qualitative(_many(s, d), bands="log_size").select("community", "size", "band", "name"))
named("sequential_shades", lambda s, d: draw.sequential(_many(s, d)).select("community", "size", "shade"))


@query
def morton_codes(s, d):
    at = layout.init(edges.nodes(planted(s, d)))
    return at.select("node", draw.morton(F.floor(F.col("x") + 128), F.floor(F.col("y") + 128), 8).alias("code"))


# ---------------------------------------------------------------- whole runs
@query
def summarise(s, d):
    x = pipeline.summarise(planted(s, d), Params(rounds=3))
    return x.drawing


@query
def stylise(s, d):
    return pipeline.stylise(g.graph(s, d, "doc_hub"), Params(rounds=3), whole_iterations=50)


@query
def svg(s, d):
    return pipeline.summarise(g.graph(s, d, "doc_hub"), Params(rounds=3)).svg()


@query
def whole_layout(s, d):
    return baselines.whole_layout(g.graph(s, d, "doc_hub"))[0]


@query
def layout_distributed(s, d):
    e = group_edges(s, d)
    return layout.run(sized(s, d).select(F.col("community").alias("node"), "size"), e, 3, engine="spark", mass="size")[0]


@query
def extract_community(s, d):
    e = planted(s, d)
    return case.extract(e, g.planted_truth(e), 7).select("src", "dst")


@query
def relayout_community(s, d):
    e = store(planted(s, d), "edges")
    return case.relayout(e, g.planted_truth(e), 7, 30)


# ---------------------------------------------------------------- baselines
named("components", lambda s, d: baselines.components(planted(s, d)))
named("edge_sample", lambda s, d: baselines.edge_sample(planted(s, d), 20).select("src", "dst"))
named("degree_filter", lambda s, d: baselines.degree_filter(planted(s, d), 4).select("src", "dst"))
named("peel_densest", lambda s, d: baselines.peel_densest(planted(s, d))[0])
named("label_propagation", lambda s, d: baselines.label_propagation(planted(s, d), 5))


@query
def attribute_supergraph(s, d):
    e = g.graph(s, d, "cust_part")
    c = g.table(s, d, "customer").select(F.col("c_custkey").alias("node"), F.col("c_nationkey").cast("bigint").alias("a"))
    p = g.table(s, d, "part").select((F.col("p_partkey") + g.SECOND).alias("node"), (F.col("p_size") + 1000).cast("bigint").alias("a"))
    return baselines.attribute_supergraph(e, F.col("a"), c.union(p))[1]


# ---------------------------------------------------------------- sources, filters, joins
named("scan_edges_pruned", lambda s, d: readers.parquet_edges(s, f"{d}/lineitem.parquet", "l_orderkey", "l_partkey", F.col("l_quantity") >= 45))
named("json_edges", lambda s, d: readers.json_edges(g.table(s, d, "events"), "user_id", "props", "k").groupBy("src", "dst").agg(F.count("*").alias("w")))
named("page_link_edges", lambda s, d: g.page_links(s, d))
named("knn_edges", lambda s, d: g.vec_knn(s, d).select("src", "dst"))
named("conversation_edges", lambda s, d: g.conv_chain(s, d).select("src", "dst"))
named("document_items", lambda s, d: g.doc_item(s, d).select("src", "dst"))
named("copurchase_edges", lambda s, d: g.copurchase(s, d).select("src", "dst"))
named("supplier_part_edges", lambda s, d: g.supp_part(s, d).select("src", "dst"))
named("customer_supplier_edges", lambda s, d: g.cust_supp(s, d).select("src", "dst"))
named("shared_line_edges", lambda s, d: g.doc_share(s, d).select("src", "dst"))
named("shared_line_hubs", lambda s, d: g.doc_hub(s, d).select("src", "dst"))  # every shared line, where the one above has those of G7
named("user_next_edges", lambda s, d: g.user_next(s, d).select("src", "dst"))
named("nation_trade", lambda s, d: g.nation_trade(s, d))
named("sample_edges", lambda s, d: baselines.edge_sample(g.graph(s, d, "order_part"), 5).select("src", "dst"))


@query
def filter_time_slice(s, d):
    e = g.table(s, d, "events").where(F.col("ts").between(F.lit("2024-01-10").cast("timestamp_ntz"), F.lit("2024-01-20").cast("timestamp_ntz")) & F.col("event_type").isin("view", "click", "purchase") & F.col("props").like('%"k"%'))
    return e.select("event_id", "user_id")


@query
def filter_null_safe_labels(s, d):
    a = planted(s, d).select("src", F.when(F.col("dst") % 3 == 0, F.col("dst")).alias("x"), F.when(F.col("dst") % 2 == 0, F.col("dst")).alias("y"))
    return a.where(F.col("x").eqNullSafe(F.col("y"))).groupBy("src").agg(F.count("*").alias("n"))


@query
def join_shuffle_hash(s, d):
    e = planted(s, d)
    return e.join(edges.degrees(e).toDF("src", "src_deg").hint("shuffle_hash"), "src").select("src", "dst", "src_deg")


@query
def degree_band_join(s, d):
    bands = s.sql("select * from values (1, 1, 2), (2, 3, 5), (3, 6, 1000000) as t(band, low, high)")
    deg = edges.degrees(planted(s, d))
    return deg.join(F.broadcast(bands), F.col("deg").between(F.col("low"), F.col("high"))).groupBy("band").agg(F.count("*").alias("n"))


@query
def interval_edges(s, d):
    """Events within an hour lie in the same hour of the clock or in neighbouring ones, so each meets three hours only."""
    hour = F.expr("timestampdiff(HOUR, timestamp_ntz'1970-01-01 00:00:00', ts)").alias("hour")
    e = g.table(s, d, "events").select("user_id", "ts", F.get_json_object("props", "$.k").cast("bigint").alias("k"), hour).where("k is not null")
    about = F.explode(F.array(F.col("hour") - 1, F.col("hour"), F.col("hour") + 1)).alias("hour")
    j = e.toDF("a", "ta", "k", "hour").join(e.select(F.col("user_id").alias("b"), F.col("ts").alias("tb"), "k", about), ["k", "hour"]).where("a < b and tb between ta - interval 1 hour and ta + interval 1 hour")
    return j.groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.count("*").alias("w"))


@query
def isolated_nodes(s, d):
    seen = planted(s, d).select((F.col("dst") - g.SECOND).alias("p_partkey"))
    return g.table(s, d, "part").select("p_partkey").join(seen, "p_partkey", "left_anti")


@query
def top_neighbours(s, d):
    e = g.graph(s, d, "supp_part")
    deg = edges.degrees(e).toDF("dst", "deg")
    w = Window.partitionBy("src").orderBy(F.desc("deg"), "dst")
    return e.join(deg, "dst").withColumn("rank", F.row_number().over(w)).where("rank <= 3").select("src", "dst", "deg", "rank")


@query
def top_neighbours_lateral(s, d):
    e = planted(s, d).select("src", "dst")
    e.createOrReplaceTempView("lateral_edges")
    return s.sql("select n.src, t.dst from (select distinct src from lateral_edges) n, lateral (select dst from lateral_edges e where e.src = n.src order by dst limit 2) t")


# ---------------------------------------------------------------- aggregates and windows
@query
def community_members_list(s, d):
    """The ten smallest members, as its SQL has it; community_members_all has all of them."""
    a = g.planted_truth(planted(s, d))
    return a.groupBy("community").agg(F.array_join(F.transform(F.slice(F.array_sort(F.collect_list("node")), 1, 10), lambda x: x.cast("string")), ",").alias("members"))


CHUNK = 1000


@query
def community_members_all(s, d):
    """Every member, in sorted lists of CHUNK at most: the members of a community whose ids divided by CHUNK are chunk."""
    a = g.planted_truth(planted(s, d)).withColumn("chunk", F.floor(F.col("node") / CHUNK))
    return a.groupBy("community", "chunk").agg(F.array_join(F.transform(F.array_sort(F.collect_list("node")), lambda x: x.cast("string")), ",").alias("members"))


@query
def last_label(s, d):
    ev = detect.copy_events(detect.admitted(planted(s, d), CAP))
    return ev.groupBy("loser").agg(F.max_by("winner", "seq").alias("last"), F.min_by("winner", "seq").alias("first"))


def _typed(s, d):
    e = planted(s, d)
    side = F.when(F.col("node") >= g.SECOND, F.lit("part")).otherwise(F.lit("customer"))
    return g.planted_truth(e).join(edges.degrees(e), "node").withColumn("side", side)


named("sizes_rollup", lambda s, d: _typed(s, d).rollup("community", "side").agg(F.sum("deg").alias("size"), F.count("*").alias("n")))
named("edges_cube", lambda s, d: _typed(s, d).cube("community", "side").agg(F.max("deg").alias("most"), F.count("*").alias("n")))


@query
def sizes_grouping_sets(s, d):
    return _typed(s, d).groupingSets([[F.col("community")], [F.col("side")], []], F.col("community"), F.col("side")).agg(F.sum("deg").alias("size"), F.grouping_id().cast("bigint").alias("gid"))


@query
def rounds_pivot(s, d):
    h = rounds.detect(store(planted(s, d), "edges"), cap_list=[2, 4]).hierarchy
    n = h.groupBy((F.col("parent") % 5).alias("part"), "round").agg(F.countDistinct("parent").alias("n"))
    return n.groupBy("part").pivot("round", [1, 2]).agg(F.first("n")).toDF("part", "round_1", "round_2")


@query
def size_rank(s, d):
    w = Window.orderBy(F.desc("n_nodes"))
    return sized(s, d).select("community", F.rank().over(w).cast("bigint").alias("rank"), F.dense_rank().over(w).cast("bigint").alias("dense"), F.percent_rank().over(w).alias("pr")).select("community", "rank", "dense", rounded("pr"))


@query
def size_cumulative_share(s, d):
    w = Window.orderBy("size", "community")
    total = F.sum("size").over(Window.partitionBy())
    return sized(s, d).select("community", (F.sum("size").over(w) / total).alias("share"), F.cume_dist().over(w).alias("cd")).select("community", rounded("share"), rounded("cd"))


@query
def edge_rate_sliding(s, d):
    e = g.table(s, d, "events").select("user_id", "event_id", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t"))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86400, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"))


@query
def prev_event(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = g.table(s, d, "events")
    return e.select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.sum("value").over(w.rowsBetween(-6, 0)).alias("v")).select("event_id", "before", "after", "first", rounded("v", 4))


@query
def top_communities(s, d):
    return _many(s, d).orderBy(F.desc("size"), "community").limit(10).select("community", "size")


def _halves(s, d):
    t = g.table(s, d, "lineitem").where(F.col("l_quantity") > 25).select(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"))
    u = g.table(s, d, "lineitem").where(F.col("l_quantity") <= 25).select(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"))
    return t, u


named("edges_common", lambda s, d: (lambda t, u: t.intersect(u))(*_halves(s, d)))
named("edges_gained", lambda s, d: (lambda t, u: t.exceptAll(u))(*_halves(s, d)))
named("edges_lost", lambda s, d: (lambda t, u: u.subtract(t))(*_halves(s, d)))
named("edges_union", lambda s, d: (lambda t, u: t.unionByName(u).distinct())(*_halves(s, d)))
named("host_of_url", lambda s, d: g.table(s, d, "pages").select("page_id", F.lower(F.regexp_extract("url", "//([^/]*)", 1)).alias("host"), F.substring_index(F.regexp_extract("url", "//([^/]*)", 1), ".", -2).alias("domain")))
named("node_neighbour_arrays", lambda s, d: planted(s, d).groupBy("src").agg(F.array_sort(F.collect_set("dst")).alias("a")).select("src", F.size("a").cast("bigint").alias("n"), F.aggregate("a", F.lit(0).cast("bigint"), lambda x, y: x + y).alias("total"), F.element_at("a", 1).alias("first")))
named("metrics_map", lambda s, d: sized(s, d).select("community", F.map_from_arrays(F.array(F.lit("size"), F.lit("n")), F.array("size", "n_nodes")).alias("m")).select("community", F.element_at("m", "size").alias("size"), F.array_join(F.array_sort(F.map_keys("m")), ",").alias("names")))
named("community_json", lambda s, d: sized(s, d).select("community", F.to_json(F.struct("community", "size", "n_nodes")).alias("j")).select("community", F.get_json_object("j", "$.size").cast("bigint").alias("size")))
named("edges_by_month", lambda s, d: g.table(s, d, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count("*").alias("n"), F.countDistinct("o_custkey").alias("customers")))
_start = lambda df: df.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))
named("edges_tumbling", lambda s, d: _start(windows.tumbling(windows.edges_of_events(g.table(s, d, "events"))).select("start", "n")))
named("edges_sliding", lambda s, d: _start(windows.sliding(windows.edges_of_events(g.table(s, d, "events")))))
named("edges_sessions", lambda s, d: _start(windows.sessions(windows.edges_of_events(g.table(s, d, "events")))))


@query
def sql_function_cells(s, d):
    register(s)
    edges.nodes(planted(s, d)).createOrReplaceTempView("planted_nodes")
    return s.sql(f"select node, affine_cell(node, 1103515245, 12345, {WIDTH}) as cell from planted_nodes")


# ---------------------------------------------------------------- streaming
@query
def streaming_detect(s, d):
    """The events as a file stream, in micro-batches, with the state that each batch leaves to the next."""
    import uuid

    base = f"{shared_dir(s)}/stream-{uuid.uuid4().hex}"
    rows = store(numbered(windows.edges_of_events(g.table(s, d, "events")), [F.col("ts"), F.col("src"), F.col("dst")], "seq").select("seq", "src", "dst").repartition(3), "stream")
    detector = attach.Detector(s, f"{base}/state", 20)
    flow = s.readStream.schema(rows.schema).option("maxFilesPerTrigger", 2).parquet(rows._stored_at)
    attach.attach(flow, detector, f"{base}/checkpoint").awaitTermination()
    return detector.state()


# ---------------------------------------------------------------- general operators on the whole customer-part graph
_GENERAL = ("degrees", "degree_histogram", "base_cap_", "admitted_edges", "assignment_", "bulk_assignment", "sketch_", "superedges", "components", "label_propagation", "summarise")
for _name in [k for k in QUERIES if any(k == x or x.endswith("_") and k.startswith(x) for x in _GENERAL)]:
    whole(_name, "cust_part")
