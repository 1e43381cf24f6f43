"""The experiments, re-expressed on the given tables. Each returns rows of (graph, setting, metric, value).

run(name, spark, sf_dir, graphs, ...) runs a whole experiment with timings; QUERIES holds the slices of them that plain
SQL can check, and the timed ones on one small graph.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.operators import baselines, detect, draw, edges, layout, measure, rounds, sketch, summary
from graphsummary.params import Params
from graphsummary.plans import case, oracles, pipeline, stages
from graphsummary.plans import queries as q
from graphsummary.sources import catalogue as g
from graphsummary.sources.storage import store

ALL = ("copurchase", "cust_part", "order_part", "supp_part", "cust_supp", "user_next", "doc_share", "page_links", "planted", "vec_knn")
METRICS = "graph string, setting string, metric string, value double"


def timed(action: Callable[[], object]) -> tuple[object, float]:
    """The result of an action and its milliseconds."""
    t = time.perf_counter()
    out = action()
    return out, 1000 * (time.perf_counter() - t)


def repeat(action: Callable[[], float], n: int = 20, keep: str = "worst") -> float:
    """A figure (higher is better) over n runs: the worst, the best or the median."""
    values = sorted(action() for _ in range(n))
    return {"worst": values[0], "best": values[-1], "median": values[len(values) // 2]}[keep]


def frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(a, str(b), c, None if v is None else float(v)) for a, b, c, v in rows], METRICS)


def _edges(s: SparkSession, d: str, name: str) -> DataFrame:
    return store(g.graph(s, d, name), name)


def _sizes(e: DataFrame, a: DataFrame) -> DataFrame:
    return summary.exact_sizes(a, edges.degrees(e))


def w1(s, d, graphs=ALL, iterations=100, whole_iterations=500, **params) -> DataFrame:
    """Main table: the summary against the whole layout."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        x = pipeline.summarise(e, Params(**({"rounds": 4, "iterations": iterations} | params)))
        (_, _), whole = timed(lambda e=e: baselines.whole_layout(e, whole_iterations))
        m = x.metrics | {"n": edges.nodes(e).count(), "q": measure.modularity(e, x.assignment).first()[0], "whole_ms": whole, "time_saved_pct": int(100 * (1 - x.metrics["total_ms"] / whole)), "speed_ratio": whole / x.metrics["total_ms"]}
        rows += [(name, "summary", k, v) for k, v in m.items()]
    return frame(s, rows)


def w2(s, d, graphs=("cust_part", "order_part", "supp_part", "doc_share", "page_links"), depths=(1, 2, 3, 4), width=None) -> DataFrame:
    """Hash functions: error and memory of the sketch, and that the graph's summary does not depend on them."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        a, t0 = timed(lambda e=e: rounds.detect(e, 4))
        deg, exact = store(edges.degrees(e), "deg"), store(_sizes(e, a.assignment), "exact")
        for k in depths:
            w = width or sketch.dims(e.count())[1]
            est, t = timed(lambda k=k, w=w, a=a, deg=deg: store(summary.sizes(a.assignment, deg, "sketch", depth=k, width=w), "est"))
            err = measure.sketch_error(est, exact.select("community", "size")).first()
            rows += [(name, k, "sn", a.metrics[-1]["sn"]), (name, k, "se", a.metrics[-1]["se"]), (name, k, "ms", t0 + t), (name, k, "mean_error", err["mean_error"]), (name, k, "max_error", err["max_error"]), (name, k, "cells", k * w)]
    return frame(s, rows)


def w3(s, d, graphs=ALL[:9], counts=(2, 3, 4)) -> DataFrame:
    """Rounds, each an independent run."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        for k in counts:
            (m,), t = timed(lambda e=e, k=k: rounds.sweep(e, [k], with_q=True))
            rows += [(name, k, c, m[c]) for c in ("sn", "se", "q")] + [(name, k, "ms", t)]
    return frame(s, rows)


def w4(s, d, graphs=("order_part", "doc_share", "page_links"), scales=(1, 3, 5)) -> DataFrame:
    """The cap times 1, 3, 5."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        for k in scales:
            m = rounds.detect(e, 4, threshold_scale=k, with_q=True)
            rows += [(name, k, c, m.metrics[-1][c]) for c in ("sn", "se", "q")] + [(name, k, "cap", m.base)]
    return frame(s, rows)


def w5(s, d, graphs=("order_part", "page_links"), fractions=(1e-3, 3e-3)) -> DataFrame:
    """The sketch's width: error and how many communities change their colour class."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        a, deg = rounds.detect(e, 4).assignment, store(edges.degrees(e), "deg")
        exact = store(_sizes(e, a).select("community", "size"), "exact")
        true = draw.qualitative(exact).select("community", F.col("band").alias("true_band"))
        for f in fractions:
            w = sketch.dims(e.count(), f)[1]
            est = store(summary.sizes(a, deg, "sketch", width=w), "est")
            err = measure.sketch_error(est, exact).first()
            moved = draw.qualitative(est).join(true, "community").where("band <> true_band").count()
            rows += [(name, f, "width", w), (name, f, "mean_error", err["mean_error"]), (name, f, "max_error", err["max_error"]), (name, f, "bands_moved", moved)]
    return frame(s, rows)


def w6(s, d, graphs=("doc_share", "page_links"), iterations=100, whole_iterations=200) -> DataFrame:
    """Three pictures of each graph: rows drawn, and how communities spread in the whole layout."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        x = pipeline.summarise(e, Params(rounds=4, iterations=iterations))
        whole = store(baselines.whole_layout(e, whole_iterations)[0], "whole")
        painted = draw.stylise(whole, x.assignment, draw.qualitative(x.supernodes))
        rows += [(name, "summary", "svg_rows", x.svg().count()), (name, "whole", "svg_rows", draw.svg(draw.plain(whole), radius_column=None).count()), (name, "stylised", "colours", painted.select("hex").distinct().count())]
        area = measure.extent(whole, x.assignment, 10.0).join(x.supernodes.select("community", "size"), "community").where("n_nodes > 1")
        rows += [(name, "whole", "size_extent_rank_corr", measure.rank_corr(area, "size", "rms_radius").first()[0]), (name, "summary", "size_radius_rank_corr", measure.rank_corr(x.drawing, "size", "radius").first()[0])]
        rows.append((name, "stylised", "mean_scatter", measure.scatter(whole, x.assignment).agg(F.avg("scatter")).first()[0]))
    return frame(s, rows)


def w7(s, d, counts=(2, 3, 4)) -> DataFrame:
    """Known groups: how well they are found."""
    e = _edges(s, d, "planted")
    truth = store(g.planted_truth(e), "truth")
    rows = [("planted", "truth", "q", measure.modularity(e, truth).first()[0])]
    for k in counts:
        a = rounds.detect(e, k, stop_when_stable=False).assignment
        rows += [("planted", k, "q", measure.modularity(e, a).first()[0]), ("planted", k, "purity", measure.purity(a, truth).first()[0]), ("planted", k, "nmi", measure.nmi(a, truth).first()[0]), ("planted", k, "blobs", measure.large_blobs(_sizes(e, a)).first()[0])]
    return frame(s, rows)


def w8(s, d, most=6) -> DataFrame:
    """Round by round on the graph of mode degree 2: inner and cross edges."""
    e = _edges(s, d, "planted")
    rows, levels = [], rounds.detect(e, most, stop_when_stable=False).hierarchy
    now = edges.nodes(e).select("node", F.col("node").alias("community"))
    for k in range(1, most + 1):
        step = levels.where(F.col("round") == k).select(F.col("child").alias("community"), "parent")
        now = store(now.join(step, "community", "left").select("node", F.coalesce("parent", "community").alias("community")), "labels")
        t = measure.edge_split(e, now).agg(F.sum("inner").alias("i"), (F.sum("cross") / 2).alias("c"), F.avg("inner").alias("m")).first()
        rows += [("planted", k, "inner", t["i"]), ("planted", k, "cross", t["c"]), ("planted", k, "inner_per_community", t["m"])]
    return frame(s, rows)


def w9(s, d, graphs=("doc_share", "page_links"), iterations=100, whole_iterations=200) -> DataFrame:
    """Case study: what clusters of similar area hold, and the largest supernode on its own."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        x = pipeline.summarise(e, Params(rounds=3, iterations=iterations))
        whole = store(baselines.whole_layout(e, whole_iterations)[0], "whole")
        j = measure.extent(whole, x.assignment, 10.0).join(measure.edge_split(e, x.assignment), "community").orderBy(F.desc("rms_radius"), "community").limit(5)
        for i, r in enumerate(j.collect()):
            rows += [(name, f"cluster {i + 1}", c, r[c]) for c in ("rms_radius", "cells", "n_nodes", "inner")]
        top = case.largest(x.supernodes)
        own = store(case.extract(e, x.assignment, top), "own")
        rows += [(name, "largest", "edges", own.count()), (name, "largest", "laid_out", case.relayout(e, x.assignment, top, iterations).count()), (name, "largest", "q_inside", rounds.detect(own, 2, with_q=True).metrics[-1]["q"])]
    return frame(s, rows)


def w10(s, d, graphs=("doc_share", "page_links")) -> DataFrame:
    """Sequential colouring."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        shades = draw.sequential(_sizes(e, rounds.detect(e, 3).assignment)).groupBy("shade").agg(F.count("*").alias("n"))
        rows += [(name, r["shade"], "communities", r["n"]) for r in shades.collect()]
    return frame(s, rows)


def w11(s, d, graphs=("doc_share", "page_links", "planted"), iterations=100, eps=0.01) -> DataFrame:
    """When the supergraph's layout stops moving."""
    rows = []
    for name in graphs:
        x = pipeline.summarise(_edges(s, d, name), Params(rounds=3, iterations=iterations))
        last = x.trace.orderBy(F.desc("iteration")).first()
        rows += [(name, iterations, "stable_iteration", measure.stable_iteration(x.trace, eps).first()[0]), (name, iterations, "last_move_share", last["max_move"] / max(last["diameter"], 1e-9)), (name, iterations, "last_swing", last["swing"])]
    return frame(s, rows)


def w12(s, d, graphs=ALL[:9], whole_iterations=500) -> DataFrame:
    """Detection time as a share of the whole layout."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        _, t = timed(lambda e=e: pipeline.merge(e, pipeline.detect(e, Params(rounds=4)), Params(rounds=4)))
        _, whole = timed(lambda e=e: baselines.whole_layout(e, whole_iterations))
        rows.append((name, "overhead", "percent", 100 * t / whole))
    return frame(s, rows)


def w13(s, d, graphs=("order_part", "planted"), n=20, whole_iterations=500) -> DataFrame:
    """The least saving over repeated runs."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)

        def saving(e=e) -> float:
            total = pipeline.summarise(e, Params(rounds=4)).metrics["total_ms"]
            return int(100 * (1 - total / timed(lambda: baselines.whole_layout(e, whole_iterations))[1]))

        rows.append((name, n, "worst_time_saved_pct", repeat(saving, n)))
    return frame(s, rows)


def w14(s, d, name="cust_part", width=257) -> DataFrame:
    """The sequential and the parallel sketch: cells that differ."""
    deg = store(edges.degrees(_edges(s, d, name)), "deg")
    a, b = sketch.build(deg, "node", "deg", 4, width), sketch.sketch_loop(deg, "node", "deg", 4, width)
    return frame(s, [(name, width, "different_cells", a.exceptAll(b).count() + b.exceptAll(a).count())])


def w15(s, d, graphs=ALL[:9], most=6) -> DataFrame:
    """Rounds until the communities stay, and the round of the best modularity."""
    rows = []
    for name in graphs:
        m = rounds.metrics_frame(s, rounds.detect(_edges(s, d, name), most, with_q=True).metrics)
        best = rounds.best_round(m).first()
        rows += [(name, most, "stable_round", rounds.converged(m).first()[0]), (name, most, "best_round", best["best_round"]), (name, most, "best_q", best["best"])]
    return frame(s, rows)


def w16(s, d, graphs=("planted", "doc_share", "user_next"), cap=3) -> DataFrame:
    """The parallel detectors against the sequential one."""
    rows = []
    for name in graphs:
        e = _edges(s, d, name)
        loop = store(detect.stream_loop(e, cap), "loop")
        for kind, a in (("exact", detect.stream(e, cap)), ("sliced", detect.stream_sliced(e, cap, 8)), ("bulk", detect.bulk(e, cap))):
            a = store(a, kind)
            rows += [(name, kind, "different_nodes", measure.agreement(loop, a).first()["different"]), (name, kind, "q", measure.modularity(e, a).first()[0])]
        rows.append((name, "loop", "q", measure.modularity(e, loop).first()[0]))
    return frame(s, rows)


def w17(s, d, graphs=ALL, count=4) -> DataFrame:
    """Modularity of all graphs, after the given rounds and at the best round."""
    rows = []
    for name in graphs:
        m = rounds.detect(_edges(s, d, name), count, with_q=True).metrics
        rows += [(name, count, "q", m[-1]["q"]), (name, count, "best_q", max(x["q"] for x in m))]
    return frame(s, rows)


def w18(s, d, splits=(1, 7, 50), cap=20) -> DataFrame:
    """The stream cut into micro-batches: nodes whose label differs from the batch run."""
    import uuid

    from graphsummary.sources.storage import shared_dir
    from graphsummary.streaming import attach

    e = _edges(s, d, "user_next")
    whole, n, rows = store(detect.stream(e, cap), "whole"), e.count(), []
    for k in splits:
        at = attach.Detector(s, f"{shared_dir(s)}/split-{uuid.uuid4().hex}", cap)
        for i in range(k):
            at.step(e.where((F.col("seq") > i * n // k) & (F.col("seq") <= (i + 1) * n // k)), i)
        rows.append(("user_next", k, "different_nodes", measure.agreement(whole, at.assignment()).first()["different"]))
    return frame(s, rows)


RUNS = {f.__name__: f for f in (w1, w2, w3, w4, w5, w6, w7, w8, w9, w10, w11, w12, w13, w14, w15, w16, w17, w18)}


def run(name: str, spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    return RUNS[name](spark, sf_dir, **options)


def table(metrics: DataFrame, metric: str) -> DataFrame:
    """One metric as a table of graphs by settings."""
    return metrics.where(F.col("metric") == metric).groupBy("graph").pivot("setting").agg(F.first("value"))


# ---------------------------------------------------------------- registered slices
#: What the costs count: layout steps of the whole graph and of the supergraph, detection rounds over both ends of each edge.
WHOLE_STEPS, SUPER_STEPS, DETECTED = 500, 100, 4
COST_GRAPHS = ("cust_part", "supp_part", "cust_supp", "planted")


def _costs(s: SparkSession, d: str) -> DataFrame:
    """(graph, whole, total, supergraph): the rows that each method reads on a graph of the given tables and its supergraph of
    the groups of ids: the whole layout, detection with the supergraph's layout, and detection alone."""
    out = None
    for name in COST_GRAPHS:
        e = store(g.GRAPHS[name](s, d), name)
        a = store(g.planted_truth(e), "groups")
        c = measure.counts(a.select("community").distinct(), summary.superedges(e, a))
        n, m = (x.agg(F.count("*").cast("double").alias("n")).scalar() for x in (a, e))
        found = 2.0 * DETECTED * m
        row = c.select(F.lit(name).alias("graph"), (WHOLE_STEPS * (n + m)).alias("whole"), (found + SUPER_STEPS * (F.col("sn") + F.col("se"))).alias("total"), found.alias("supergraph"))
        out = row if out is None else out.unionByName(row)
    return store(out, "costs")


def w1_graph_sizes(s, d):
    out = None
    for name in ("copurchase", "cust_part", "order_part", "supp_part", "cust_supp", "user_next", "planted"):
        e = g.graph(s, d, name)
        deg = edges.degrees(e)
        top = edges.degree_histogram(deg).agg(F.max_by("deg", F.struct("n", -F.col("deg"))).alias("mode")).scalar()
        row = deg.agg(F.lit(name).alias("graph"), F.count("*").alias("n"), (F.sum("deg") / 2).cast("bigint").alias("m"), F.floor(F.sum("deg") / F.count("*")).alias("average")).select("*", top.alias("mode"))
        out = row if out is None else out.unionByName(row)
    return out


def w1_summary_counts(s, d):
    return q.QUERIES["supergraph_counts"](s, d)


def w2_sketch_by_depth(s, d):
    e = g.graph(s, d, "planted")
    deg = store(edges.degrees(e), "deg")
    out = None
    for k in (1, 2, 3, 4):
        est = sketch.estimate(sketch.build(deg, "node", "deg", k, q.WIDTH), deg, "node", k, q.WIDTH)
        row = measure.sketch_error(est, deg).select(F.lit(k).alias("depth"), F.round("mean_error", 6).alias("mean_error"), "max_error")
        out = row if out is None else out.unionByName(row)
    return out


def w3_rounds(s, d):
    e = store(g.graph(s, d, "planted"), "edges")
    m = rounds.metrics_frame(s, rounds.detect(e, cap_list=[2, 4], with_q=True).metrics)
    return m.select("round", "sn", "se", F.round("q", 6).alias("q"))


def w4_cap_scale(s, d):
    e = store(g.graph(s, d, "order_part"), "edges")
    out = None
    for k in (1, 3, 5):
        row = detect.admitted(e, 4 * k).agg(F.lit(k).alias("scale"), F.count("*").alias("admitted"))
        out = row if out is None else out.unionByName(row)
    return out


def w5_sketch_by_width(s, d):
    deg = store(edges.degrees(g.graph(s, d, "planted")), "deg")
    out = None
    for w in (257, 769):
        est = sketch.estimate(sketch.build(deg, "node", "deg", 4, w), deg, "node", 4, w)
        row = measure.sketch_error(est, deg).select(F.lit(w).alias("width"), F.round("mean_error", 6).alias("mean_error"), "max_error")
        out = row if out is None else out.unionByName(row)
    return out


def w6_bands(s, d):
    return q.QUERIES["colour_bands"](s, d).groupBy("band", "name").agg(F.count("*").alias("n"), F.sum("size").alias("total"))


def w10_shades(s, d):
    return q.QUERIES["sequential_shades"](s, d).groupBy("shade").agg(F.count("*").alias("n"), F.max("size").alias("most"))


def w8_cross_by_round(s, d):
    e = store(g.graph(s, d, "planted"), "edges")
    out = None
    for k in (1, 2):
        a = rounds.detect(e, cap_list=[2, 4][:k]).assignment
        row = measure.edge_split(e, a).agg(F.lit(k).alias("round"), F.sum("inner").alias("inner"), (F.sum("cross") / 2).cast("bigint").alias("cross"))
        out = row if out is None else out.unionByName(row)
    return out


def w3_independent(s, d):
    """2, 3 and 4 rounds, each a run of its own, with the caps that the graph's own mode gives."""
    e = store(g.graph(s, d, "planted"), "edges")
    rows = [(m["rounds"], m["sn"], m["se"], m["q"]) for m in rounds.sweep(e, [2, 3, 4], with_q=True)]
    return s.createDataFrame(rows, "rounds int, sn bigint, se bigint, q double")


def w8_all_rounds(s, d):
    """Inner and cross edges after each of six rounds."""
    return w8(s, d, 6)


def w9_extent_first_step(s, d):
    """Found communities in the whole layout as it starts: spread, cells, inner edges, and these of all possible ones."""
    e = store(g.graph(s, d, "planted"), "edges")
    a = store(detect.stream(e, q.CAP), "labels")
    spread = measure.extent(layout.init(edges.nodes(e)), a, 10.0)
    both = spread.join(measure.edge_split(e, a).select("community", "inner"), "community", "left").withColumn("inner", F.coalesce("inner", F.lit(0)))
    density = F.when(F.col("n_nodes") > 1, 2 * F.col("inner") / (F.col("n_nodes") * (F.col("n_nodes") - 1)))
    return both.select("community", "n_nodes", F.round("rms_radius", 6).alias("rms_radius"), "cells", "inner", F.round(density, 6).alias("density"))


def w9_largest_community_edges(s, d):
    e = store(g.graph(s, d, "planted"), "edges")
    a = store(detect.stream(e, q.CAP), "labels")
    top = case.largest(_sizes(e, a))
    return case.extract(e, a, top).select("src", "dst")


def w12_overhead(s, d):
    return _costs(s, d).select("graph", F.round(measure.stylise_overhead(F.col("supergraph"), F.col("whole")), 6).alias("percent"))


def w13_worst(s, d):
    return _costs(s, d).agg(F.min(measure.time_saved_pct(F.col("whole"), F.col("total"))).alias("least"), F.max(measure.time_saved_pct(F.col("whole"), F.col("total"))).alias("most"))


def time_saved(s, d):
    return _costs(s, d).select("graph", measure.time_saved_pct(F.col("whole"), F.col("total")).cast("bigint").alias("saved"), F.round(measure.speed_ratio(F.col("whole"), F.col("total")), 6).alias("ratio"))


def best_round(s, d):
    """The best round of the planted graph's own rounds, and the one after which their communities stay."""
    m = store(w3_rounds(s, d), "rounds")
    stable = rounds.converged(m).scalar()
    return rounds.best_round(m).select("best_round", "best", stable.alias("stable_round"))


def w15_best_round(s, d):
    return rounds.best_round(w3_rounds(s, d))


def w17_modularity_truths(s, d):
    e = g.graph(s, d, "vec_knn").select("src", "dst", "w")
    labels = g.table(s, d, "embeddings").select(F.col("vec_id").alias("node"), F.col("label").cast("bigint").alias("community"))
    c = g.conv_chain(s, d)
    conv = edges.nodes(c).select("node", F.floor(F.col("node") / 1000).alias("community"))
    p = g.graph(s, d, "planted")
    out = None
    for name, x, a in (("vec_knn", e, labels), ("conv_chain", c, conv), ("planted", p, g.planted_truth(p))):
        row = measure.modularity(x, a).select(F.lit(name).alias("graph"), F.round("q", 6).alias("q"))
        out = row if out is None else out.unionByName(row)
    return out


def w7_truth(s, d):
    return q.QUERIES["modularity"](s, d)


def w14_sketch_agrees(s, d):
    return w14(s, d, "planted").select("metric", F.col("value").cast("bigint").alias("value"))


def w16_detectors_agree(s, d):
    return w16(s, d, ("planted",)).where("setting = 'exact' and metric = 'different_nodes'").select("metric", F.col("value").cast("bigint").alias("value"))


def w18_stream_agrees(s, d):
    return w18(s, d, (1, 5)).groupBy("metric").agg(F.sum("value").cast("bigint").alias("value"))


def w1_main_small(s, d):
    return w1(s, d, ("doc_hub",), 50, 100)


def w11_stability(s, d):
    return w11(s, d, ("doc_hub",))


def w7_found(s, d):
    """The found communities against the planted groups, each figure measured on the run's own communities."""
    return w7(s, d)


def stage_metrics(s, d):
    """Memory, spill and shuffle of each stage of detection over the whole customer-part graph."""
    return stages.stage_metrics(s, lambda: detect.stream(g.graph(s, d, "cust_part"), 20).write.format("noop").mode("overwrite").save())


QUERIES = {
    f.__name__: f
    for f in (w1_graph_sizes, w1_summary_counts, w1_main_small, w2_sketch_by_depth, w3_rounds, w4_cap_scale, w5_sketch_by_width, w6_bands, w7_truth, w8_cross_by_round, w9_largest_community_edges, w10_shades, w3_independent, w8_all_rounds, w9_extent_first_step,
              w11_stability, w12_overhead, w13_worst, w14_sketch_agrees, w15_best_round, w16_detectors_agree, w17_modularity_truths, w18_stream_agrees, time_saved, best_round, w7_found, stage_metrics)
}


# ---------------------------------------------------------------- their SQL
def _lists() -> dict[str, str]:
    o, line = oracles, "orders join lineitem on o_orderkey = l_orderkey"
    return {
        "copurchase": "select distinct a.l_partkey as src, b.l_partkey as dst from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey",
        "cust_part": f"select distinct o_custkey as src, l_partkey + {o.SECOND} as dst from {line}", "order_part": "select distinct l_orderkey as src, l_partkey + 1000000000 as dst from lineitem",
        "supp_part": f"select distinct l_suppkey as src, l_partkey + {o.SECOND} as dst from lineitem", "cust_supp": f"select distinct o_custkey as src, l_suppkey + {o.SECOND} as dst from {line}",
        "user_next": "select distinct least(a, b) as src, greatest(a, b) as dst from (select user_id as a, lead(user_id) over (order by ts, event_id) as b from events) where b is not null and a <> b",
        "planted": f"select distinct o_custkey as src, l_partkey + {o.SECOND} as dst from {line} where o_custkey % 15 = l_partkey % 15 or (o_custkey * 7919 + l_partkey * 104729) % 100 < 2",
    }


def _graph_sizes() -> str:
    lists = _lists()
    one = "select '{0}' as graph, count(*) as n, cast(sum(deg) / 2 as bigint) as m, cast(floor(sum(deg) / count(*)) as bigint) as average, (select deg from (select deg, count(*) as c from d_{0} group by deg) order by c desc, deg limit 1) as mode from d_{0}"
    ctes = ", ".join(f"x_{k} as ({v}), d_{k} as (select node, count(*) as deg from (select src as node from x_{k} union all select dst from x_{k}) group by node)" for k, v in lists.items())
    return f"with {ctes} " + " union all ".join(one.format(k) for k in lists)


def _cost_rows() -> str:
    """CTE costs(graph, w, t, s)."""
    group = f"(case when {{0}} >= {oracles.SECOND} then {{0}} - {oracles.SECOND} else {{0}} end) % 15"
    ctes = ", ".join(f"x_{k} as ({_lists()[k]}), n_{k} as (select src as node from x_{k} union select dst from x_{k}), p_{k} as (select {group.format('src')} as a, {group.format('dst')} as b from x_{k})" for k in COST_GRAPHS)
    one = "select '{0}' as graph, (select count(*) from n_{0}) as n, (select count(*) from x_{0}) as m, (select count(distinct %s) from n_{0}) as sn, (select count(*) from (select distinct least(a, b), greatest(a, b) from p_{0} where a <> b)) as se" % group.format("node")
    rows = " union all ".join(one.format(k) for k in COST_GRAPHS)
    return f"{ctes}, counted as ({rows}), costs as (select graph, {WHOLE_STEPS}.0 * (n + m) as w, {2 * DETECTED}.0 * m + {SUPER_STEPS} * (sn + se) as t, {2 * DETECTED}.0 * m as s from counted)"


def _errors(settings: list[tuple[str, int, int]], column: str) -> str:
    o = oracles
    parts = []
    for label, depth, width in settings:
        est = f"with {o.matrix('deg', 'node', 'deg', depth, width)}, {o.estimate('deg', 'node', depth, width)} select {label} as {column}, round(avg(est - deg), 6) as mean_error, max(est - deg) as max_error from est join deg using (node)"
        parts.append(f"select * from ({est})")
    return f"with {o.PLANTED}, {o.DEGREES} " + " union all ".join(parts)


_SPLIT_A, _SPLIT_B = oracles.split("alabel"), oracles.split("two")
_PAIRS = "select count(*) from (select distinct least(a.community, b.community), greatest(a.community, b.community) from e join {0} a on src = a.node join {0} b on dst = b.node where a.community <> b.community)"
_ROUND_ROWS = f"""select 1 as round, (select count(distinct community) from alabel) as sn, ({_PAIRS.format('alabel')}) as se, (select {oracles.Q.replace('parts', 'pa')}) as q
union all select 2, (select count(distinct community) from two), ({_PAIRS.format('two')}), (select {oracles.Q.replace('parts', 'pb')})"""
_BOTH = f"{oracles.TWO}, {_SPLIT_A.replace('ab as', 'xa as').replace('from ab', 'from xa').replace('parts as', 'pa as')}, {_SPLIT_B.replace('ab as', 'xb as').replace('from ab', 'from xb').replace('parts as', 'pb as')}"


def _truths() -> str:
    o = oracles
    knn = o.ORACLES["knn_edges"].removeprefix("with ")
    head, _, body = knn.rpartition(" select distinct ")
    made = {
        "vec_knn": (f"{head}, e_vec_knn as (select distinct {body})", "select vec_id as node, cast(label as bigint) as community from embeddings"),
        "conv_chain": (f"e_conv_chain as ({o.ORACLES['conversation_edges']})", "select distinct node, node // 1000 as community from (select src as node from e_conv_chain union select dst from e_conv_chain)"),
        "planted": (f"{o.PLANTED}, {o.DEGREES}, {o.TRUTH}, e_planted as (select src, dst from e)", "select * from truth"),
    }
    ctes, rows = [], []
    for k, (e, t) in made.items():
        s = o.split(f"t_{k}", f"e_{k}").replace("ab as", f"ab_{k} as").replace("from ab", f"from ab_{k}").replace("parts as", f"p_{k} as")
        ctes.append(f"{e}, t_{k} as ({t}), {s}")
        rows.append(f"select '{k}' as graph, {o.Q.replace('from parts', f'from p_{k}')}")
    return f"with {', '.join(ctes)} " + " union all ".join(rows)


ORACLES = {
    "w1_graph_sizes": _graph_sizes(),
    "w1_summary_counts": oracles.ORACLES["supergraph_counts"],
    "w2_sketch_by_depth": _errors([(str(k), k, oracles.WIDTH) for k in (1, 2, 3, 4)], "depth"),
    "w3_rounds": oracles.plain(_BOTH, _ROUND_ROWS),
    "w4_cap_scale": oracles.plain(
        f"raw as (select distinct l_orderkey as src, l_partkey + 1000000000 as dst from lineitem), e as (select row_number() over (order by {oracles.ORDER}) as seq, src, dst from raw), " + ", ".join(oracles.found(cap=4 * k, p=f"c{k}") for k in (1, 3, 5)),
        " union all ".join(f"select {k} as scale, count(*) as admitted from c{k}adm" for k in (1, 3, 5))),
    "w5_sketch_by_width": _errors([(str(w), 4, w) for w in (257, 769)], "width"),
    "w6_bands": f"select band, name, count(*) as n, cast(sum(size) as bigint) as total from ({oracles.ORACLES['colour_bands']}) group by band, name",
    "w7_truth": oracles.ORACLES["modularity"],
    "w8_cross_by_round": oracles.plain(_BOTH, "select 1 as round, cast(sum(\"inner\") as bigint) as \"inner\", cast(sum(\"cross\") / 2 as bigint) as \"cross\" from pa union all select 2, cast(sum(\"inner\") as bigint), cast(sum(\"cross\") / 2 as bigint) from pb"),
    "w9_largest_community_edges": oracles.plain(f"{oracles._MANY}, top as (select community from sizes order by size desc, community limit 1)", "select e.src, e.dst from e join label a on e.src = a.node join label b on e.dst = b.node join top on a.community = top.community and b.community = top.community"),
    "w9_extent_first_step": oracles.plain(
        f"{oracles.ONE}, spots as (select node, 1.0 as mass from deg), {oracles.START}, {oracles.split('label')}, spread as (select community, count(*) as n_nodes, round(sqrt(var_pop(x) + var_pop(y)), 6) as rms_radius, count(distinct (floor(x / 10), floor(y / 10))) as cells from pos join label using (node) group by community)",
        "select community, n_nodes, rms_radius, cells, coalesce(\"inner\", 0) as \"inner\", round(case when n_nodes > 1 then 2.0 * coalesce(\"inner\", 0) / (n_nodes * (n_nodes - 1)) end, 6) as density from spread left join parts using (community)"),
    "w10_shades": f"select shade, count(*) as n, max(size) as most from ({oracles.ORACLES['sequential_shades']}) group by shade",
    "w12_overhead": f"with {_cost_rows()} select graph, round(100.0 * s / w, 6) as percent from costs",
    "w13_worst": f"with {_cost_rows()} select cast(min(floor(100 * (1 - t / w))) as bigint) as least, cast(max(floor(100 * (1 - t / w))) as bigint) as most from costs",
    "time_saved": f"with {_cost_rows()} select graph, cast(floor(100 * (1 - t / w)) as bigint) as saved, round(w / t, 6) as ratio from costs",
    "best_round": f"with r as ({oracles.plain(_BOTH, _ROUND_ROWS)}), b as (select round, sn, lag(sn) over (order by round) as before from r) select (select round from r order by q desc, round limit 1) as best_round, (select max(q) from r) as best, (select max(round) from b where before is null or before <> sn) as stable_round",
    "w14_sketch_agrees": "select 'different_cells' as metric, 0 as value",
    "w15_best_round": f"select round as best_round, q as best from ({oracles.plain(_BOTH, _ROUND_ROWS)}) order by q desc, round limit 1",
    "w16_detectors_agree": "select 'different_nodes' as metric, 0 as value",
    "w17_modularity_truths": _truths(),
    "w18_stream_agrees": "select 'different_nodes' as metric, 0 as value",
}
