"""The graphs of the experiments, built from the given tables."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphsummary.operators.edges import canonical, with_arrival
from graphsummary.operators.order import with_next

SECOND, PARTS = 10_000_000, 1_000_000_000  # offsets of the second side of bipartite graphs
GROUPS = 15


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def pairs(df: DataFrame, src: Column, dst: Column) -> DataFrame:
    """Distinct pairs with weight 1, ends as they are."""
    return df.select(src.cast("bigint").alias("src"), dst.cast("bigint").alias("dst")).where("src is not null and dst is not null").distinct().withColumn("w", F.lit(1).cast("bigint"))


def _order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return orders.join(table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey"), F.col("o_orderkey") == F.col("l_orderkey"))


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    both = lines.toDF("o", "a").join(lines.toDF("o", "b"), "o").where("a < b")
    return pairs(both, F.col("a"), F.col("b"))


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs(_order_lines(spark, sf_dir), F.col("o_custkey"), F.col("l_partkey") + SECOND)


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs(table(spark, sf_dir, "lineitem"), F.col("l_orderkey"), F.col("l_partkey") + PARTS)


def supp_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs(table(spark, sf_dir, "lineitem"), F.col("l_suppkey"), F.col("l_partkey") + SECOND)


def cust_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs(_order_lines(spark, sf_dir), F.col("o_custkey"), F.col("l_suppkey") + SECOND)


def user_next_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst): the user of each event and of the next one, by ranges of the order over the narrow event columns."""
    e = table(spark, sf_dir, "events").select("ts", "event_id", "user_id")
    return with_next(e, [F.col("ts"), F.col("event_id")], "user_id", "dst").select(F.col("user_id").alias("src"), "dst").where("dst is not null")


def user_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    return canonical(user_next_rows(spark, sf_dir))


LINE_LEAST, LINE_MOST = 20, 50


def shared_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, line) of the lines that stand in 2 to 50 documents."""
    d = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("raw"))
    lines = d.select("doc_id", F.trim("raw").alias("line")).where(F.length("line") >= LINE_LEAST).distinct()
    some = lines.groupBy("line").agg(F.count("*").alias("n")).where(F.col("n").between(2, LINE_MOST)).select("line")
    return lines.join(some, "line")


def doc_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = shared_lines(spark, sf_dir)
    both = lines.toDF("line", "a").join(lines.toDF("line", "b"), "line").where("a < b")
    return pairs(both, F.col("a"), F.col("b"))


def doc_hub(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links from the smallest doc_id that holds a line to every other one: each line in two or more documents counts, short and
    frequent ones too, at one link for a document and line. Documents are connected as by all pairs."""
    d = table(spark, sf_dir, "documents").where("doc_id is not null").select("doc_id", F.explode(F.split("text", "\n")).alias("raw"))
    lines = d.select("doc_id", F.trim("raw").alias("line")).where("line <> ''").distinct()
    hubs = lines.groupBy("line").agg(F.min("doc_id").alias("hub"), F.count("*").alias("n")).where("n > 1").select("line", "hub")
    return pairs(lines.join(hubs, "line").where("hub <> doc_id"), F.col("hub"), F.col("doc_id"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst) as text: a page's host and the targets of its links."""
    p = table(spark, sf_dir, "pages").select("url", "html")
    host = F.regexp_extract("url", "//([^/]*)", 1)
    links = p.select(host.alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("dst"))
    return links.where("src <> '' and dst <> ''").distinct()


def page_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    return canonical(page_links(spark, sf_dir).select(F.xxhash64("src").alias("src"), F.xxhash64("dst").alias("dst")))


def planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer-part pairs of the same group of 15, and two in a hundred of the others."""
    c, p = F.col("o_custkey"), F.col("l_partkey")
    kept = _order_lines(spark, sf_dir).where((c % GROUPS == p % GROUPS) | ((c * 7919 + p * 104729) % 100 < 2))
    return pairs(kept, c, p + SECOND)


def planted_truth(edges: DataFrame) -> DataFrame:
    """(node, community): the group that each node was planted in."""
    node = F.explode(F.array("src", "dst")).alias("node")
    own = F.when(F.col("node") >= SECOND, F.col("node") - SECOND).otherwise(F.col("node")) % GROUPS
    return edges.select(node).distinct().select("node", own.alias("community"))


def nation_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directed, loops kept: customer nation to supplier nation, weight is the number of lines."""
    c, s = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    j = _order_lines(spark, sf_dir).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    return j.groupBy(F.col("c_nationkey").cast("bigint").alias("src"), F.col("s_nationkey").cast("bigint").alias("dst")).agg(F.count("*").alias("w"))


def event_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select("user_id", F.get_json_object("props", "$.k").cast("bigint").alias("k"))
    return pairs(e, F.col("user_id"), F.col("k") + SECOND)


NEIGHBOURS = 5
#: Vectors whose id is divisible by this ask for their neighbours.
ASKING = 20
#: Bytes of asking vectors that every executor holds at a time, and how many of them meet a batch at once.
HELD_BYTES, CHUNK = 32 << 20, 512


def _nearest(held, k: int):
    """(a, b, s): for each asking vector the k best rows of a task, by dot product from large to small, then by id. Products
    of whole blocks select the rows that may be among them; those are summed again in the order of the dimensions."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, asked, asks = held.value
        m, d = asked.shape
        best, whose = np.full((m, k), -np.inf), np.full((m, k), np.iinfo(np.int64).max)
        for batch in batches:
            for lo in range(0, batch.num_rows, 4096):
                b, rows, valid = _vectors(batch.slice(lo, 4096), d)
                for q in range(0, m, CHUNK):
                    end = min(m, q + CHUNK)
                    s = asked[q:end] @ rows.T
                    s[np.isnan(s)] = np.inf
                    s[:, ~valid], s[~asks[q:end]] = -np.inf, -np.inf
                    least = best[q:end, -1]
                    if len(b) > k + 1 and (least == -np.inf).any():  # one row may be the vector itself
                        least = np.maximum(least, np.partition(s, len(b) - k - 1, axis=1)[:, len(b) - k - 1])
                    finite = np.abs(s[np.isfinite(s)])
                    i, j = np.nonzero(s >= (least - 1e-9 * (1 + finite.max(initial=0)))[:, None])
                    i, j = (x[ids[q + i] != b[j]] for x in (i, j))
                    if not len(i):
                        continue
                    exact = np.zeros(len(i))
                    for c in range(d):
                        exact += asked[q + i, c] * rows[j, c]
                    exact[np.isnan(exact)] = np.inf
                    exact[np.isneginf(s[i, j])] = -np.inf
                    hit = np.unique(i)
                    of = np.concatenate([i, np.repeat(hit, k)])
                    score, other = np.concatenate([exact, best[q + hit].ravel()]), np.concatenate([b[j], whose[q + hit].ravel()])
                    order = np.lexsort((other, -score, of))
                    of, score, other = of[order], score[order], other[order]
                    rank = np.arange(len(of)) - np.searchsorted(of, of)
                    keep = rank < k
                    best[q + of[keep], rank[keep]], whose[q + of[keep], rank[keep]] = score[keep], other[keep]
        i, j = np.nonzero(whose < np.iinfo(np.int64).max)
        yield pa.RecordBatch.from_arrays([pa.array(ids[i]), pa.array(whose[i, j]), pa.array(best[i, j])], names=["a", "b", "s"])

    return run


def _vectors(batch: pa.RecordBatch, d: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, vectors in double precision, and which are whole: not null, without nulls, of d dimensions."""
    given = batch.column(1).to_pylist() if batch.column(1).null_count or batch.column(1).flatten().null_count else None
    if given is None:
        sizes, flat = np.diff(batch.column(1).offsets.to_numpy()), batch.column(1).flatten().to_numpy().astype(np.float64)
        if (sizes == d).all():
            return batch.column(0).to_numpy(), flat.reshape(-1, d), np.ones(batch.num_rows, bool)
        given = batch.column(1).to_pylist()
    valid = np.array([x is not None and len(x) == d and None not in x for x in given], bool)
    rows = np.zeros((len(given), d))
    for i in np.flatnonzero(valid):
        rows[i] = given[i]
    return batch.column(0).to_numpy(), rows, valid


def vec_knn(spark: SparkSession, sf_dir: str, k: int = NEIGHBOURS) -> DataFrame:
    """Links from every vector whose id is divisible by ASKING to its k nearest of all vectors by dot product, exactly. The
    asking vectors go to the executors in parts of HELD_BYTES, and all vectors are read for each part."""
    v = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("bigint").alias("vec_id"), F.col("embedding").cast("array<float>").alias("e")).where("vec_id is not null")
    asking = v.where(F.col("vec_id") % ASKING == 0)
    n, d = asking.agg(F.count("*"), F.max(F.size("e"))).first()
    parts, found = max(1, -(-n * 8 * max(d or 0, 1) // HELD_BYTES)), None
    for part in range(parts):
        own = asking.where(F.pmod(F.xxhash64("vec_id"), F.lit(parts)) == part).toArrow().combine_chunks().to_batches()
        held = _vectors(own[0], max(d, 0)) if own else (np.zeros(0, np.int64), np.zeros((0, 1)), np.zeros(0, bool))
        got = v.mapInArrow(_nearest(spark.sparkContext.broadcast(held), k), "a bigint, b bigint, s double")
        found = got if found is None else found.union(got)
    near = found.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("s"), "b"))).where(F.col("r") <= k)
    return canonical(near, "a", "b")


def conv_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    node = F.col("conv_id") * 1000 + F.col("turn")
    after = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    return t.select(node.alias("src"), F.col("turn").alias("t"), after.alias("next"), "conv_id").where("next = t + 1").select("src", (F.col("conv_id") * 1000 + F.col("next")).alias("dst"), F.lit(1).cast("bigint").alias("w"))


def doc_item(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents and the benchmark passages that they hold; the passages are few and sent to every executor."""
    items = table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("item"))
    held = F.broadcast(items) if items.count() <= 10_000 else items
    j = table(spark, sf_dir, "documents").select("doc_id", "text").join(held, F.col("text").contains(F.col("item")))
    return pairs(j, F.col("doc_id"), F.col("item_id") + SECOND)


#: Two triangles and the edge between them, in order.
TOY = ((1, 2), (1, 3), (2, 3), (4, 5), (4, 6), (5, 6), (3, 4))


def toy(spark: SparkSession, sf_dir: str = "") -> DataFrame:
    return spark.createDataFrame([(i + 1, a, b, 1) for i, (a, b) in enumerate(TOY)], "seq bigint, src bigint, dst bigint, w bigint")


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "copurchase": copurchase, "cust_part": cust_part, "order_part": order_part, "supp_part": supp_part, "cust_supp": cust_supp, "user_next": user_next, "doc_share": doc_share, "doc_hub": doc_hub,
    "page_links": page_graph, "planted": planted, "event_key": event_key, "vec_knn": vec_knn, "conv_chain": conv_chain, "doc_item": doc_item,
}


def graph(spark: SparkSession, sf_dir: str, name: str, dense: bool = True) -> DataFrame:
    """An edge list (seq, src, dst, w) of the catalogue, in the arrival order of its hash."""
    if name == "toy":
        return toy(spark)
    return with_arrival(GRAPHS[name](spark, sf_dir), dense=dense).select("seq", "src", "dst", "w")
