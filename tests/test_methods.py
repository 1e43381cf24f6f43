"""Golden values of the fixtures, equal results of independent implementations, and edge cases."""

import io
from contextlib import redirect_stdout
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from graphsummary.operators import baselines, detect, draw, edges, layout, measure, order, rounds, sketch, summary
from graphsummary.params import Params
from graphsummary.plans import pipeline
from graphsummary.sources import catalogue, readers
from graphsummary.sources.storage import shared_dir, store
from graphsummary.streaming import attach

E = "seq bigint, src bigint, dst bigint, w bigint"


def labels(df):
    return [r["community"] for r in df.orderBy("node").collect()]


@pytest.mark.parametrize(("cap", "tie", "want", "q"), [
    (1, "source", [2, 2, 3, 5, 5, 6], 0.010204), (1, "hold", [1, 2, 3, 4, 5, 6], -0.173469), (2, "source", [2, 2, 2, 5, 5, 5], 0.357143),
    (2, "hold", [1, 2, 1, 4, 5, 4], -0.010204), (3, "source", [2, 2, 5, 5, 5, 5], 0.122449),
])
def test_toy(spark, cap, tie, want, q):
    e = catalogue.toy(spark)
    found = detect.stream(e, cap, tie=tie)
    assert labels(found) == want == labels(detect.stream_loop(e, cap, tie=tie))
    assert measure.modularity(e, found).first()[0] == pytest.approx(q, abs=1e-6) == measure.modularity_pairs(e, found).first()[0]


def test_joiner_counting_stalls(spark):
    assert labels(detect.stream_loop(catalogue.toy(spark), 3, count="joiner", tie="hold")) == [1, 2, 3, 4, 5, 6]


@pytest.mark.parametrize(("cap", "admit", "tie"), [(2, "le", "source"), (3, "lt", "hold"), (4, "le", "lower_id")])
def test_parallel_is_sequential(spark, sf, cap, admit, tie):
    e = store(catalogue.graph(spark, sf, "planted"), "e")
    got = measure.agreement(detect.stream(e, cap, admit, tie), detect.stream_loop(e, cap, admit, tie=tie)).first()
    assert got["different"] == got["missing"] == 0


def test_less_than_is_one_cap_less(spark, sf):
    e = store(catalogue.graph(spark, sf, "doc_share"), "e")
    got = measure.agreement(detect.stream(e, 4, "lt"), detect.stream(e, 3, "le")).first()
    assert got["different"] == got["missing"] == 0


def test_rounds_golden(spark, sf):
    e = store(catalogue.graph(spark, sf, "planted"), "e")
    m = rounds.detect(e, cap_list=[2, 4, 8], with_q=True).metrics
    assert [(x["sn"], x["se"]) for x in m] == [(153, 274), (55, 118), (25, 23)]
    assert [round(x["q"], 6) for x in m] == [0.372979, 0.572769, 0.435886]


def test_rank_is_limited_before_the_shuffle(spark, sf):
    plan = io.StringIO()
    with redirect_stdout(plan):
        detect.admitted(catalogue.graph(spark, sf, "planted", dense=False), 3).explain()
    assert plan.getvalue().count("WindowGroupLimit") >= 2
    assert "CartesianProduct" not in plan.getvalue()


def test_edge_cases(spark):
    for rows in ([], [(1, 1, 2, 1)], [(1, -5, 3_000_000_000, 1), (2, 3_000_000_000, 7, 1)], [(i, 0, i, 1) for i in range(1, 300)], [(i, i, i + 1, 1) for i in range(1, 40)], [(40 - i, i, i + 1, 1) for i in range(1, 40)]):
        e = store(spark.createDataFrame(rows, E), "e")
        got = measure.agreement(detect.stream(e, 2), detect.stream_loop(e, 2)).first()
        assert got["different"] == got["missing"] == 0
    raw = spark.createDataFrame([(1, 1), (1, 2), (2, 1), (None, 3), (2, 1)], "src bigint, dst bigint")
    assert [tuple(r) for r in edges.canonical(raw, repeats="sum").collect()] == [(1, 2, 3)]
    assert edges.base_cap(spark.createDataFrame([], E)) == 1


def test_sketch_golden(spark):
    keys = spark.range(1, 11).select(F.col("id").alias("k"))
    for depth, want in ((1, [1, 5, 5, 9, 9, 13, 13, 17, 17, 10]), (2, [1, 5, 4, 6, 9, 13, 12, 14, 9, 10]), (4, [1, 2, 4, 6, 9, 13, 12, 14, 9, 10])):
        est = sketch.estimate(sketch.build(keys, "k", "k", depth, 7), keys, "k", depth, 7)
        assert [r["est"] for r in est.orderBy("k").collect()] == want


def test_colours_golden(spark):
    sizes = spark.range(1, 41).select(F.col("id").alias("community"), F.col("id").alias("size"))
    bands = {r["band"]: r["n"] for r in draw.qualitative(sizes).groupBy("band").agg(F.count("*").alias("n")).collect()}
    assert bands == {0: 28, 1: 2, 2: 2} | dict.fromkeys(range(3, 11), 1)


def test_layout_step_golden(spark):
    at = spark.createDataFrame([(1, -1.0, 0.0, 1.0, 0.0, 0.0, 0.0, 0.0), (2, 1.0, 0.0, 1.0, 0.0, 0.0, 0.0, 0.0)], "node bigint, x double, y double, mass double, fx double, fy double, pfx double, pfy double")
    f = store(layout.add_forces(at, layout.gravity(at), layout.attraction(at, spark.createDataFrame([(1, 2, 1)], "src bigint, dst bigint, w bigint")), layout.repulsion_exact(at)), "f")
    assert {r["node"]: r["fx"] for r in f.collect()} == {1: -37.0, 2: 37.0}
    for rule, x in (("paper", -6.164414), ("published", -6.223950)):
        assert layout.move(f, layout.speeds(f, 1.0, rule)).where("node = 1").first()["x"] == pytest.approx(x, abs=1e-6)


def test_tree_repulsion_is_close(spark):
    at = store(layout.init(spark.range(800).withColumnRenamed("id", "node")), "at")
    a, b = layout.repulsion_exact(at).toDF("node", "ax", "ay"), layout.repulsion_tree(at)
    err = a.join(b, "node").agg(F.avg(F.hypot(F.col("ax") - F.col("fx"), F.col("ay") - F.col("fy")) / F.hypot("ax", "ay"))).first()[0]
    assert err < 0.05


def test_hubs_are_ranked_by_ranges(spark):
    rows = [(i, 0, i + 1) for i in range(300)] + [(300 + i, i % 40 + 1, 1000 + i) for i in range(200)] + [(500, 7, 7)]
    e = spark.createDataFrame([(a * 7919 % 100003, b, c, 1) for a, b, c in rows], "seq bigint, src bigint, dst bigint, w bigint")
    key = e.withColumn("seq", F.struct(F.col("seq").alias("k0"), "src", "dst"))
    for x in (e, key):
        for limit in (None, 120):
            whole, split = (sorted((str(r["seq"]), r["node"], r["deg"]) for r in detect.ranked(x, limit, hub=h).collect()) for h in (1 << 20, 4))
            assert whole == split and len(whole) == (2 * len(rows) if limit is None else 2 * len(rows) - 180)


def clumped(spark):
    """700 nodes in a place a ten-thousandth as wide as the whole, 100 about it, 20 on one point."""
    rows = layout.init(spark.range(820).withColumnRenamed("id", "node"))
    scale = F.when(F.col("node") < 700, 1e-4).when(F.col("node") < 800, 1.0).otherwise(0.0)
    return store(rows.withColumns({"x": F.col("x") * scale + F.when(F.col("node") >= 800, 30.0).otherwise(0.0), "y": F.col("y") * scale, "mass": F.col("node") % 3 + 1.0}), "clumped")


def off(a, b):
    j = a.toDF("node", "ax", "ay").join(b, "node")
    row = j.agg(F.count("*").alias("n"), F.avg(F.hypot(F.col("ax") - F.col("fx"), F.col("ay") - F.col("fy")) / F.hypot("ax", "ay")).alias("err")).first()
    return row["n"], row["err"]


def test_opened_repulsion(spark):
    at = clumped(spark)
    exact = store(layout.repulsion_exact(at), "exact")
    n, err = off(exact, layout.repulsion_opened(at, theta=0.0))
    assert n == 820 and err < 1e-6
    errors = [off(exact, layout.repulsion_opened(at, theta=t))[1] for t in (0.3, 0.9)]
    assert errors[0] < errors[1] < 0.05 and errors[0] < 0.01
    assert layout.repulsion_opened(at.limit(0)).count() == 0
    one = layout.repulsion_opened(at.limit(1)).first()
    assert (one["fx"], one["fy"]) == (0.0, 0.0)


def test_opened_repulsion_by_blocks(spark):
    """Blocks of any size give the same forces, crowded and massless nodes included, and no node's way is written as rows."""
    at = clumped(spark)
    some = store(at.withColumn("mass", F.when(F.col("node") % 5 == 0, 0.0).otherwise(F.col("mass"))), "some")
    for rows, deepest in ((at, None), (some, 8)):
        whole = store(layout.repulsion_opened(rows, deepest=deepest), "whole")
        both = whole.toDF("node", "ax", "ay").join(layout.repulsion_opened(rows, deepest=deepest, block=16), "node")
        apart, size = F.hypot(F.col("ax") - F.col("fx"), F.col("ay") - F.col("fy")), F.hypot("ax", "ay")
        n, most = both.agg(F.count("*"), F.max(apart / (size + 1.0))).first()
        assert n == 820 and most < 1e-9
    assert layout.repulsion_opened(at.withColumn("mass", F.lit(0.0)), block=16).agg(F.count("*"), F.sum(F.abs("fx"))).first()[:2] == (820, 0.0)
    many = store(layout.init(spark.range(5000).withColumnRenamed("id", "node")), "many")
    folder = Path(shared_dir(spark).removeprefix("file:"))
    held = lambda: sum(p.stat().st_size for p in folder.rglob("*.parquet"))
    before = held()
    assert layout.repulsion_opened(many).count() == 5000
    assert held() - before < 5000 * 100


def test_task_and_cluster_layouts_agree(spark):
    e = catalogue.toy(spark)
    n = edges.nodes(e)
    a, b = layout.run(n, e, 5, engine="task")[0], layout.run(n, e, 5, engine="spark")[0].toDF("node", "bx", "by", "bm")
    assert a.join(b, "node").agg(F.max(F.abs(F.col("x") - F.col("bx")))).first()[0] < 1e-6


def test_summary(spark, sf):
    x = pipeline.summarise(catalogue.graph(spark, sf, "planted"), Params(rounds=3, iterations=20, size_method="exact"))
    assert x.drawing.count() == x.supernodes.count() == x.metrics["sn"]
    assert x.supernodes.agg(F.sum("size")).first()[0] == 2 * x.metrics["m"]
    assert x.svg().where("line = '</svg>'").count() == 1


def test_contraction_keeps_modularity(spark, sf):
    e = store(catalogue.graph(spark, sf, "planted"), "e")
    a = catalogue.planted_truth(e)
    split = measure.edge_split(e, a).agg(F.sum("inner"), F.sum("cross") / 2, F.sum("volume")).first()
    assert split[0] + split[1] == e.count() and split[2] == 2 * e.count()
    assert summary.superedges(e, a).agg(F.sum("w")).first()[0] == split[1]


@pytest.mark.parametrize("cuts", [1, 3])
def test_micro_batches_equal_one_pass(spark, sf, tmp_path, cuts):
    e = store(catalogue.graph(spark, sf, "user_next"), "e")
    whole, n = detect.stream(e, 20), e.count()
    at = attach.Detector(spark, str(tmp_path), 20)
    for i in range(cuts):
        part = e.where((F.col("seq") > i * n // cuts) & (F.col("seq") <= (i + 1) * n // cuts))
        at.step(part, i)
        at.step(part, i)  # a batch that runs again changes nothing
    got = measure.agreement(whole, at.assignment()).first()
    assert got["different"] == got["missing"] == 0
    full = sketch.build(at.state(), "community", "deg", 4, 1025)
    assert not full.exceptAll(at.sketch()).count()


def test_components_and_peeling(spark):
    rows = [(1, 1, 2, 1), (2, 2, 3, 1), (3, 10, 11, 1)]
    assert sorted(map(tuple, baselines.components(spark.createDataFrame(rows, E)).collect())) == [(1, 1), (2, 1), (3, 1), (10, 10), (11, 10)]
    clique = [(i * 10 + j, i, j, 1) for i in range(5) for j in range(i)] + [(100 + i, i + 10, i + 11, 1) for i in range(20)]
    found, density = baselines.peel_densest(spark.createDataFrame(clique, E))
    assert density >= 2.0 / 2.2 and {r[0] for r in found.collect()} >= set(range(5))


def test_text_edges(spark, tmp_path):
    (tmp_path / "g.txt").write_text("# a comment\n1 2\n3\t4\t2.5\n% other\n5,6\n\nx y\n")
    assert sorted(map(tuple, readers.text_edges(spark, str(tmp_path / "g.txt")).collect())) == [(1, 2, 1.0), (3, 4, 2.5), (5, 6, 1.0)]


def test_params_are_checked():
    with pytest.raises(ValueError):
        Params(tie="other")
    with pytest.raises(ValueError):
        Params(rounds=0)


def test_order_by_ranges(spark):
    from pyspark.sql import Window

    df = spark.range(5000).select(((F.col("id") * 7919) % 5003).alias("k"), (F.col("id") % 3).alias("g"), F.col("id").alias("v"))
    w = Window.orderBy("g", "k")
    n = F.row_number().over(w)
    want = df.select("v", n.cast("bigint").alias("n"), F.sum("v").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("s"), F.lead("v").over(w).alias("next"), F.ntile(7).over(w).cast("bigint").alias("tile"))
    keys = [F.col("g"), F.col("k")]
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    run = order.with_next(order.running(df, keys, n=F.lit(1).cast("bigint"), s=F.col("v")), keys, "v", "next")
    got = run.select("v", "n", "s", "next", order.tile(F.col("n"), F.lit(5000), 7).cast("bigint").alias("tile"))
    assert sorted(map(tuple, got.collect()), key=repr) == sorted(map(tuple, want.collect()), key=repr)
    spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    assert order.numbered(df.limit(0), keys, "n").count() == 0 and order.with_next(df.limit(0), keys, "v", "x").count() == 0


def test_components_by_rounds(spark, monkeypatch):
    """The same labels whether one task finishes the edges or rounds do, on a path, a star and random edges."""
    import importlib
    import random

    module = importlib.import_module("graphsummary.operators.components")
    rng = random.Random(6)
    rows = [(i, i + 1) for i in range(400)] + [(1000, 1000 + i) for i in range(1, 300)] + [(rng.randrange(2000, 2600), rng.randrange(2000, 2600)) for _ in range(350)] + [(5, None), (7, 7)]
    e = spark.createDataFrame(rows, "src bigint, dst bigint")
    want = sorted(map(tuple, module.components(e).collect()))
    assert (400, 0) in want and (1299, 1000) in want and 7 in [x for x, _ in want]
    monkeypatch.setattr(module, "FEW", 40)
    assert sorted(map(tuple, module.components(e).collect())) == want
    assert module.components(e.limit(0)).count() == 0
