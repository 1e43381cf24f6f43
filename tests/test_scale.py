"""Forms of queries that have to hold on larger tables, held against plain ones on small input."""

import datetime
import io
import time
from contextlib import redirect_stdout

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphsummary.llm import exact_dedup
from graphsummary.operators import baselines, layout, measure
from graphsummary.plans import oracles, queries, workloads
from graphsummary.sources import catalogue
from graphsummary.sources.storage import store
from tests.compare import same


def plan_of(df) -> str:
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain()
    return out.getvalue()


def test_modularity_over_pairs_of_degrees(spark):
    """repeated edges and a node without a community; nodes never meet nodes."""
    rows = [(1, 2), (1, 3), (2, 3), (2, 3), (3, 4), (4, 5), (5, 6), (4, 6), (6, 7), (7, 8), (8, 9)]
    label = {1: 0, 2: 0, 3: 0, 4: 1, 5: 1, 6: 1, 7: 1, 8: 2}
    e, a = spark.createDataFrame(rows, "src bigint, dst bigint"), spark.createDataFrame(list(label.items()), "node bigint, community bigint")
    both = rows + [(y, x) for x, y in rows]
    k = {n: sum(x == n for x, _ in both) for n in label}
    want = sum(both.count((i, j)) - k[i] * k[j] / len(both) for i in label for j in label if label[i] == label[j]) / len(both)
    got = measure.modularity_pairs(e, a)
    assert got.first()[0] == pytest.approx(want, abs=1e-12)
    assert "CartesianProduct" not in plan_of(got)


def test_interval_edges_meet_by_the_hour(spark, tmp_path):
    """just an hour apart, over the edge of hours and before 1970; hours are keys of the join."""
    at = lambda *x: datetime.datetime(*x)
    rows = [(0, 1, at(2024, 1, 1, 0, 59, 59)), (1, 2, at(2024, 1, 1, 1, 59, 59)), (2, 3, at(2024, 1, 1, 2, 0, 0)), (3, 1, at(2024, 1, 1, 2, 0, 0)), (4, 4, at(1969, 12, 31, 23, 30)), (5, 5, at(1970, 1, 1, 0, 30)), (6, 6, at(1969, 12, 31, 22, 29))]
    spark.createDataFrame([(i, u, t, '{"k": 7}') for i, u, t in rows], "event_id bigint, user_id bigint, ts timestamp_ntz, props string").write.parquet(f"{tmp_path}/events.parquet")
    got = queries.QUERIES["interval_edges"](spark, str(tmp_path))
    want = {(a, b) for _, a, s in rows for _, b, t in rows if a < b and abs(s - t) <= datetime.timedelta(hours=1)}
    assert {(r["src"], r["dst"]) for r in got.collect()} == want
    assert "hour" in next(x for x in plan_of(got).splitlines() if "Join" in x)


def test_neighbours_of_asking_vectors(spark, sf, tmp_path, monkeypatch):
    """F8: equal vectors, a null one and one of zeros, asking vectors in several parts; no join of all vectors with all."""
    import random

    draw = random.Random(5)
    rows = [(i, [draw.choice([0.0, 0.5, 1.0]) for _ in range(4)]) for i in range(300)] + [(300, None), (301, [0.0] * 4)] + [(i, [1.0] * 4) for i in range(302, 320)]
    spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").repartition(3).write.parquet(f"{tmp_path}/embeddings.parquet")
    monkeypatch.setattr(catalogue, "HELD_BYTES", 200)
    got = queries.QUERIES["knn_edges"](spark, str(tmp_path))
    want = set()
    for a, x in rows[::20]:
        score = sorted((float("inf") if x is None or y is None else -sum(p * q for p, q in zip(x, y, strict=True)), b) for b, y in rows if b != a)
        want |= {(min(a, b), max(a, b)) for _, b in score[:5]}
    assert {tuple(r) for r in got.collect()} == want
    assert "NestedLoop" not in plan_of(got) and "CartesianProduct" not in plan_of(got)


def test_neighbours_equal_their_sql(spark, sf):
    assert same(queries.QUERIES["knn_edges"](spark, sf), oracles.ORACLES["knn_edges"], sf)


def test_modularity_of_asking_vectors(spark, sf):
    """the same links under known labels."""
    assert same(workloads.QUERIES["w17_modularity_truths"](spark, sf), workloads.ORACLES["w17_modularity_truths"], sf)
    assert "NestedLoop" not in plan_of(catalogue.vec_knn(spark, sf))


@pytest.mark.parametrize("name", ["best_round", "stable_iteration", "time_saved", "w12_overhead", "w13_worst"])
def test_measures_read_the_given_tables(spark, sf, name):
    """F13 to F17: figures of the given tables, not of rows in the code."""
    made = queries.QUERIES | workloads.QUERIES
    sql = oracles.ORACLES | workloads.ORACLES
    assert same(made[name](spark, sf), sql[name], sf)
    assert "lineitem" in sql[name]


def test_layout_by_blocks_is_the_layout_of_one_task(spark, monkeypatch):
    """F2 to F5, F10 and F11: a graph beyond one task takes the same steps by blocks, not as joins."""
    n = spark.range(5000).withColumnRenamed("id", "node")
    e = spark.range(9000).select((F.col("id") * 7 % 5000).alias("src"), (F.col("id") * 31 % 4999 + 1).alias("dst"), F.lit(2).alias("w")).where("src <> dst")
    one, trace = layout.run(n, e, 4, engine="task", all_pairs=0, attraction_="log")
    monkeypatch.setattr(layout, "TASK_NODES", 1000)
    monkeypatch.setattr(layout, "repulsion_tree", None)
    two, again = layout.run(n, e, 4, attraction_="log")
    j = one.join(two.toDF("node", "bx", "by", "bm"), "node").agg(F.count("*"), F.max(F.hypot(F.col("x") - F.col("bx"), F.col("y") - F.col("by")))).first()
    assert j[0] == 5000 and j[1] < 1e-5
    for a, b in zip(trace.orderBy("iteration").collect(), again.orderBy("iteration").collect(), strict=True):
        assert tuple(b) == pytest.approx(tuple(a), rel=1e-6)


def test_whole_layout_runs_all_its_iterations(spark, sf):
    """as many steps as the operator's default."""
    want, trace = baselines.whole_layout(catalogue.graph(spark, sf, "doc_hub"))
    assert trace.count() == 500
    got = queries.QUERIES["whole_layout"](spark, sf)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_cells_push_as_they_are_defined(monkeypatch):
    """leaf cells that look up together what pushes them, against each node and each cell by itself."""
    draw = np.random.default_rng(2)
    x, y = np.concatenate([draw.normal(size=(2, 400)), draw.normal(size=(2, 200)) / 50, np.full((2, 40), 0.5)], 1)
    m = draw.integers(0, 4, len(x)).astype(float)
    monkeypatch.setattr(layout, "PAIRS_AT_ONCE", 700)
    g = layout._grids(x, y, m)
    cell = np.empty((len(x), 2), int)
    cell[g["order"]] = np.stack(np.divmod(g["key"], 1 << g["levels"]), 1)
    fx, fy = np.zeros(len(x)), np.zeros(len(x))

    def push(i, ox, oy, om):
        dx, dy = x[i] - ox, y[i] - oy
        d2 = dx * dx + dy * dy
        f = np.where(d2 > 1e-9, 80.0 * m[i] * om / np.maximum(d2, 1e-9), 0.0)
        fx[i] += (f * dx).sum()
        fy[i] += (f * dy).sum()

    for i in range(len(x)):
        for level in range(2, g["levels"] + 1):
            at = cell >> (g["levels"] - level)
            far = (abs(at - at[i]).max(1) > 1) & (abs((at >> 1) - (at[i] >> 1)).max(1) <= 1)
            for c in np.unique(at[far], axis=0):
                own = (at == c).all(1)
                if m[own].sum():
                    push(i, *(np.array([np.average(v[own], weights=m[own])]) for v in (x, y)), m[own].sum())
        near = abs(cell - cell[i]).max(1) <= 1
        push(i, x[near], y[near], m[near])
    for a, b in zip(layout._cells(x, y, m, 80.0), (fx, fy), strict=True):
        assert a == pytest.approx(b, rel=1e-9, abs=1e-6)
    alone = layout._grids(*(np.array([v]) for v in (3.0, 4.0, 1.0)))
    assert [v.tolist() for v in layout._push_block(alone, 0, 1, 80.0)] == [[0.0], [0.0]]


def test_far_outliers_do_not_crowd_the_cells(monkeypatch):
    draw = np.random.default_rng(1)
    x, y = draw.normal(size=(2, 3000))
    x[:10], y[:10] = x[:10] * 300, y[:10] * 300
    m = draw.integers(1, 4, 3000).astype(float)
    monkeypatch.setattr(layout, "NEAR_PAIRS", 60)
    g, (ex, ey) = layout._grids(x, y, m), layout._pairs(x, y, m, 80.0)
    fx, fy = layout._push_block(g, 0, 3000, 80.0)
    assert np.diff(g["first"]).max() < 300
    assert np.mean(np.hypot(fx - ex[g["order"]], fy - ey[g["order"]]) / np.hypot(ex, ey)[g["order"]]) < 0.01


def test_every_text_is_named(spark, monkeypatch):
    """texts that occur once get their number from their blocks too."""
    given, named = [], exact_dedup.block_names

    def spy(texts, *rest):
        given.extend(r["row"] for r in texts.select("row").collect())
        return named(texts, *rest)

    monkeypatch.setattr(exact_dedup, "block_names", spy)
    monkeypatch.setattr(exact_dedup, "HOT", 1)  # the blocks of a's in several tasks
    rows = [(1, "a" * 300), (2, "a" * 300), (3, "b"), (4, None), (5, ""), (6, "a" * 299 + "c")]
    got = {tuple(r)[:4] for r in exact_dedup.exact_groups(spark.createDataFrame(rows, "doc_id bigint, text string"), block=64).collect()}
    assert len(set(given)) == 6
    assert got == {(1, 2, 2, False), (2, 2, 2, True), (3, 3, 1, True), (4, 5, 2, False), (5, 5, 2, True), (6, 6, 1, True)}


def test_stored_tables_leave_no_shuffle_files(spark):
    """Check finding on disk: what a stored table was shuffled by goes with its write, and the setting is as it was."""

    def files() -> set[str]:
        return {f.getName() for f in spark._jvm.java.util.ArrayList(spark._jvm.scala.jdk.javaapi.CollectionConverters.asJava(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles())) if f.getName().startswith("shuffle_")}

    key, before = "spark.sql.classic.shuffleDependency.fileCleanup.enabled", files()
    was = spark.conf.get(key, None)
    df = spark.range(20_000).groupBy((F.col("id") % 7000).alias("k")).agg(F.count("*").alias("n"))
    stored = store(df, "counted")
    for _ in range(50):
        if not files() - before:
            break
        time.sleep(0.1)
    assert not files() - before
    assert spark.conf.get(key, None) == was
    assert sorted(map(tuple, stored.collect())) == sorted(map(tuple, df.collect())) == sorted(map(tuple, df.collect()))
    with pytest.raises(Exception, match="DIVIDE_BY_ZERO"):
        store(spark.range(3).select(F.expr("1 / id")), "failing")
    assert spark.conf.get(key, None) == was
