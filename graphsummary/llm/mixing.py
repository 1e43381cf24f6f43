"""Mixing sources to target weights by a min-cost flow over membership patterns.

Documents may belong to several sources. They are aggregated by the set of sources they belong to; a flow routes each
pattern's words to its sources' quotas, where the r-th pass over the same words costs more than the one before (a
convex repetition cost). What a pattern gives is then taken from seeded documents: whole passes over all of them, and
one further pass over a part chosen by hash. The part is fixed for each size class, large documents first, and what a
class misses or exceeds is made up for by the next smaller one.

Null and empty texts have no words and are taken zero times. A null source is a source of its own. Repeated rows are
separate documents that share their fate. An empty table gives no rows. A very long text is counted by one expression and
never leaves Spark. Columns of docs named copies and taken are replaced; all others stay.
"""

from __future__ import annotations

import heapq
import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm.common import documents, small, store

#: Most membership patterns that the flow is solved over, on the driver.
MAX_PATTERNS = 20_000
#: Hash buckets of each pattern and size class from which the partial pass is made up.
BUCKETS = 256
WORD = r"[^\x20\x09-\x0D]+"


def fill_targets(sizes: dict, weights: dict, total: float, most: float) -> dict:
    """Share total by weight; a target stops at most times its source's size, the rest is shared again by weight."""
    out, open_ = {}, {s for s in sizes if sizes[s] > 0}
    out.update({s: 0.0 for s in sizes if sizes[s] <= 0})
    rest = float(total)
    while open_:
        weight = sum(weights[s] for s in open_)
        over = {s for s in open_ if rest * weights[s] / weight > most * sizes[s]}
        if not over:
            return out | {s: rest * weights[s] / weight for s in open_}
        out |= {s: float(most * sizes[s]) for s in over}
        rest -= sum(out[s] for s in over)
        open_ -= over
    return out


def route(capacity: dict[tuple, int], quota: dict, passes: int) -> dict[tuple, dict]:
    """Words that each pattern (a tuple of sources) gives to each of its sources.

    A min-cost flow by phases: node potentials from shortest distances, then as much flow as all cheapest ways take
    together, level by level. The arc from the origin to a pattern has `passes` parallel copies of the pattern's size,
    with costs 0, 1, 2, ..., so there are few distances and few phases. Fills the quotas as far as the capacities reach.
    """
    patterns, sources = sorted(capacity), sorted(quota)
    node = {("p", p): i + 2 for i, p in enumerate(patterns)} | {("s", s): len(patterns) + i + 2 for i, s in enumerate(sources)}
    n, tiny = len(node) + 2, 1e-6
    to: list[int] = []  # an arc's head, room and cost; its reverse follows it
    room: list[float] = []
    cost: list[int] = []
    near: list[list[int]] = [[] for _ in range(n)]

    def add(a: int, b: int, r: float, c: int) -> None:
        for x, y, most, price in ((a, b, r, c), (b, a, 0.0, -c)):
            near[x].append(len(to))
            to.append(y)
            room.append(most)
            cost.append(price)

    for p in patterns:
        for r in range(passes):
            add(0, node["p", p], float(capacity[p]), r)
        for s in p:
            if s in quota:
                add(node["p", p], node["s", s], math.inf, 0)
    for s in sources:
        add(node["s", s], 1, float(quota[s]), 0)
    height = [0] * n
    while True:
        dist, heap = [math.inf] * n, [(0, 0)]
        dist[0] = 0
        while heap:
            d, a = heapq.heappop(heap)
            if d > dist[a]:
                continue
            for k in near[a]:
                if room[k] > tiny and (e := d + cost[k] + height[a] - height[to[k]]) < dist[to[k]]:
                    dist[to[k]] = e
                    heapq.heappush(heap, (e, to[k]))
        if dist[1] == math.inf:
            break
        height = [h + min(d, dist[1]) for h, d in zip(height, dist, strict=True)]
        free = lambda a, k: room[k] > tiny and cost[k] + height[a] == height[to[k]]
        while True:  # all cheapest ways together
            level, queue = {0: 0}, [0]
            for a in queue:
                for k in near[a]:
                    if to[k] not in level and free(a, k):
                        level[to[k]] = level[a] + 1
                        queue.append(to[k])
            if 1 not in level:
                break
            tried, path, at = [0] * n, [], 0
            while True:
                if at == 1:
                    flow = min(room[k] for k in path)
                    for k in path:
                        room[k] -= flow
                        room[k ^ 1] += flow
                    first = next(i for i, k in enumerate(path) if room[k] <= tiny)  # the earliest arc that is full
                    at = to[path[first] ^ 1]
                    del path[first:]
                elif tried[at] < len(near[at]):
                    k = near[at][tried[at]]
                    if level.get(to[k], -1) == level[at] + 1 and free(at, k):
                        path.append(k)
                        at = to[k]
                    else:
                        tried[at] += 1
                elif path:
                    at = to[path.pop() ^ 1]
                    tried[at] += 1
                else:
                    break
    source_of = {i: s for (kind, s), i in node.items() if kind == "s"}
    return {p: {source_of[to[k]]: room[k ^ 1] for k in near[node["p", p]] if k % 2 == 0 and to[k] in source_of} for p in patterns}


def words_in(text: str) -> Column:
    """The number of words; none in a null. Each word becomes one letter, so that no list of words is made."""
    letters = F.translate(F.regexp_replace(F.col(text), rf"[\x20\x09-\x0D]*{WORD}", "x"), " \t\n\x0b\x0c\r", "")
    return F.coalesce(F.length(letters), F.lit(0)).cast("bigint")


def _parts(parts: DataFrame, plan: DataFrame) -> DataFrame:
    """(pattern, size_class, below): for each size class of a pattern, the first bucket that the partial pass leaves out.
    Classes go from large to small, and what one misses or exceeds is made up for by the next."""
    own = parts.groupBy("pattern", "size_class").agg(F.sort_array(F.collect_list(F.struct("bucket", F.col("words").cast("bigint").alias("words")))).alias("own"), F.sum("words").cast("double").alias("sum"))  # BUCKETS at most
    classes = F.sort_array(F.collect_list(F.struct("size_class", "own", "sum")), asc=False).alias("classes")
    all_ = own.groupBy("pattern").agg(classes, F.greatest(F.sum("sum"), F.lit(1.0)).alias("total")).join(plan, "pattern")

    def nearest(buckets: Column, aim: Column) -> Column:
        def step(now: Column, b: Column) -> Column:
            run = now["run"] + b["words"]
            nearer = F.abs(run - now["aim"]) < F.abs(now["sum"] - now["aim"])
            return F.struct(now["aim"].alias("aim"), run.alias("run"), F.when(nearer, run).otherwise(now["sum"]).alias("sum"), F.when(nearer, b["bucket"] + 1).otherwise(now["below"]).alias("below"))

        none = F.lit(0).cast("bigint")
        start = F.struct(aim.alias("aim"), none.alias("run"), none.alias("sum"), F.lit(0).alias("below"))
        return F.aggregate(buckets, start, step)

    def cut(now: Column, c: Column) -> Column:
        found = nearest(c["own"], F.col("extra") * c["sum"] / F.col("total") + now["carry"])
        made = F.struct((found["aim"] - found["sum"]).alias("carry"), F.struct(c["size_class"].alias("size_class"), found["below"].alias("below")).alias("cut"))
        return F.aggregate(F.array(made), now, lambda old, m: F.struct(m["carry"].alias("carry"), F.concat(old["cuts"], F.array(m["cut"])).alias("cuts")))  # found once

    start = F.struct(F.lit(0.0).alias("carry"), F.array().cast("array<struct<size_class:int,below:int>>").alias("cuts"))
    return all_.select("pattern", F.explode(F.aggregate("classes", start, cut)["cuts"]).alias("cut")).select("pattern", "cut.*")


def mix(docs: DataFrame, quota: dict[str, float], memberships: Column, size: str, doc_id: str = "doc_id", passes: int = 3, seed: int = 11, counted: DataFrame | None = None) -> DataFrame:
    """Add `copies` and `taken` to docs: how often the mix repeats the document, and the words it takes.

    memberships: array<string> of the sources that a document counts for. quota: words wanted from each source. counted: the
    same rows with only what memberships, size and doc_id need, where docs are costly to read twice.
    """
    names = F.array_sort(F.array_distinct(F.coalesce(F.filter(memberships, lambda s: s.isNotNull()), F.array().cast("array<string>"))))
    tags = {
        "__pattern": F.to_json(names),
        "__class": F.when(F.col(size) > 0, F.floor(F.log2(F.col(size).cast("double"))).cast("int")).otherwise(-1),
        "__bucket": F.pmod(F.xxhash64(F.col(doc_id), F.lit(seed)), F.lit(BUCKETS)).cast("int"),
    }
    tagged = docs.drop(*({"copies", "taken"} - {size, doc_id})).withColumns(tags)
    narrow = tagged if counted is None else counted.withColumns(tags)
    parts = store(narrow.where("__class >= 0").groupBy(F.col("__pattern").alias("pattern"), F.col("__class").alias("size_class"), F.col("__bucket").alias("bucket")).agg(F.sum(size).alias("words")), "buckets")
    patterns = parts.groupBy("pattern").agg(F.sum("words").alias("words"))
    rows = patterns.limit(MAX_PATTERNS + 1).collect()
    if len(rows) > MAX_PATTERNS:
        raise ValueError(f"more than {MAX_PATTERNS} membership patterns; group sources first")
    import json

    capacity = {tuple(json.loads(r["pattern"])): int(r["words"]) for r in rows}
    given = {p: sum(to.values()) for p, to in route({p: c for p, c in capacity.items() if p}, quota, passes).items()}
    plan = []
    for r in rows:
        flow, words = given.get(tuple(json.loads(r["pattern"])), 0.0), int(r["words"])
        whole = min(passes, int(flow / words + 1e-9))
        plan.append((r["pattern"], whole, max(0.0, flow - whole * words) if whole < passes else 0.0))
    plan_df = F.broadcast(docs.sparkSession.createDataFrame(plan, "pattern string, whole int, extra double"))
    cut = store(_parts(parts, plan_df).join(plan_df, "pattern"), "parts")
    cut = small(cut.select(F.col("pattern").alias("__pattern"), F.col("size_class").alias("__class"), F.col("below").alias("__below"), F.col("whole").alias("__whole")))
    copies = F.coalesce(F.col("__whole") + (F.col("__bucket") < F.col("__below")).cast("int"), F.lit(0))
    return tagged.join(cut, ["__pattern", "__class"], "left").withColumn("copies", copies).withColumn("taken", F.col("copies") * F.col(size)).drop("__pattern", "__class", "__bucket", "__below", "__whole")


WEIGHTS, PASSES = (5.0, 2.0, 1.0), 3


def source_key(source: str) -> Column:
    """A text that keeps null apart from any source name."""
    return F.coalesce(F.concat(F.lit("="), F.col(source)), F.lit("~"))


def source_targets(sized: DataFrame, key: str, size: str, weights: tuple[float, ...] = WEIGHTS, passes: int = PASSES) -> dict[str, tuple[int, float]]:
    """Size and target of each source: weights go round the sources by code point, null last."""
    rows = sized.groupBy(key).agg(F.sum(size).alias("size")).limit(MAX_PATTERNS + 1).collect()
    if len(rows) > MAX_PATTERNS:
        raise ValueError(f"more than {MAX_PATTERNS} sources")
    sizes = {r[0]: int(r["size"] or 0) for r in rows}
    weight = {s: weights[i % len(weights)] for i, s in enumerate(sorted(sizes))}
    targets = fill_targets(sizes, weight, sum(sizes.values()), passes)
    return {s: (sizes[s], targets[s]) for s in sizes}


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    sized = store(docs.select("doc_id", source_key("source").alias("key"), words_in("text").alias("size")), "sizes")
    targets = source_targets(sized, "key", "size")
    table = spark.createDataFrame([(s, *v) for s, v in targets.items()], "key string, source_size bigint, target double")
    mixed = mix(sized, {s: t for s, (_, t) in targets.items()}, F.array("key"), "size")
    return mixed.join(F.broadcast(table), "key").select("doc_id", "size", "source_size", "target", F.col("taken").cast("bigint").alias("taken"), "copies")
