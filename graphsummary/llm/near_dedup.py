"""Near-duplicate groups by MinHash with tensored banding.

A document is the set of its distinct five-word shingles (64-bit hashes); documents with equal sets form one class. Two
small collections of sub-keys, each made of ROWS min-hashes, stand for a class's signature; a table's key combines one
sub-key of the first collection with one of the second, so SUB + SUB sub-keys serve SUB * SUB tables and the number of
min-hashes is about the square root of what as many separate tables would take. Classes with an equal table key (a cell)
are candidates; a link is confirmed on the full sets. At the least similarity of 0.75 a sub-key agrees with probability
0.75 ** 4, and a pair misses all 784 tables with probability below 5e-5; no cell or number of partners is capped. Keys are
only combined from sub-keys that another class has too, which loses no equal key.

The members of a cell are compared with one of them (a star), and what is linked is contracted. Then the cells of a first
sub-key are put together, and only those that hold several components go on. There, exact bounds come before any pair is
made: shingles that at most RARE open classes have list their pairs (a bounded number each); all other pairs can have
frequent shingles only in common, and a class whose frequent shingles cannot reach the similarity leaves. In rounds,
members outside a cell's largest component become centres, GROWTH times as many each time; the join itself rules out pairs
of one component, of sizes that do not fit, and those that could not be similar enough if each of PARTS parts of the hash
space had the smaller number of shingles in common. Every pair of a cell is confirmed, ruled out by a bound or inside one
component in the end. The joins can be split by Spark where a cell is hot, and nothing is gathered in one task.

Null and empty texts, and texts without words, have the empty set, are linked with nothing and stay. Rows that share a
doc_id are one document with several texts: each row keeps its own n_shingles and they share a component. A null
doc_id joins the component of its text; a component of null ids only has a null component_id and stays. An empty table
gives no rows. Other columns of docs are left out, whatever their names. A text is turned into arrays whole, about 30
bytes for each of its own; it is never cut.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm.common import as_long, discard, documents, mix, read, slices, small, store, words
from graphsummary.operators.components import components

SHINGLE, PERCENT = 5, 75
ROWS, SUB = 4, 28
SEED = 20231
#: Shingles of at most so many open classes list their pairs.
RARE = 6
#: Parts of the hash space in which shared shingles are bounded, and how many of a part's shingles have a bit of their own.
PARTS, LEVELS = 128, 8
#: Centres of a cell grow so many times each round.
GROWTH = 256
HALVES, WORDS = PARTS // 64, PARTS // 64 * LEVELS
#: Text for each pass over the min-hashes: the arrays should stay in a core's cache.
PIECE = 1 << 18

_RNG = np.random.default_rng(SEED)
_HIGH = (_RNG.integers(0, 1 << 31, (2 * SUB * ROWS,)) * 2 + 1).astype(np.uint32)
_LOW = (_RNG.integers(0, 1 << 31, (2 * SUB * ROWS,)) * 2 + 1).astype(np.uint32)
_PLACE = (_RNG.integers(0, 1 << 62, (SHINGLE,)) * 2 + 1).astype(np.uint64)


def shingle_sets(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each text's distinct shingles in order, joined, and the offsets of the texts among them."""
    w, at = words(data, offsets)
    n = np.diff(at)
    owner = np.repeat(np.arange(len(n)), n)
    whole = np.zeros(0, np.uint64)
    if len(w) >= SHINGLE:
        m = len(w) - SHINGLE + 1
        whole = sum((w[j : m + j] * _PLACE[j] for j in range(SHINGLE)), np.zeros(m, np.uint64))
        inside = np.arange(m) + SHINGLE <= at[owner[:m] + 1]
        whole, of = mix(whole[inside]), owner[:m][inside]
    else:
        of = np.zeros(0, np.int64)
    short = np.flatnonzero((n > 0) & (n < SHINGLE))
    if len(short):
        one = [mix(np.array([(w[at[i] : at[i + 1]] * _PLACE[: n[i]]).sum() + np.uint64(n[i])], np.uint64))[0] for i in short]
        at_short = np.searchsorted(of, short)
        whole, of = np.insert(whole, at_short, one), np.insert(of, at_short, short)
    ends = np.searchsorted(of, np.arange(len(n) + 1))
    for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
        whole[a:b].sort()
    if not len(whole):
        return whole, ends
    keep = np.ones(len(whole), bool)
    keep[1:] = whole[1:] != whole[:-1]
    keep[ends[:-1][ends[:-1] < len(whole)]] = True
    return whole[keep], np.concatenate([[0], np.cumsum(keep)])[ends]


def sub_keys(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """(2 * SUB, sets) sub-keys; every set has a value."""
    high, low = (values >> np.uint64(32)).astype(np.uint32), values.astype(np.uint32)
    a, b = np.empty_like(high), np.empty_like(low)
    out = np.empty((2 * SUB, len(starts)), np.uint64)
    for i in range(2 * SUB):
        key = np.full(len(starts), i, np.uint64)
        for j in range(i * ROWS, (i + 1) * ROWS):
            np.multiply(high, _HIGH[j], out=a)
            np.multiply(low, _LOW[j], out=b)
            a += b
            key = mix(key * np.uint64(0x9E3779B97F4A7C15) + np.minimum.reduceat(a, starts))
        out[i] = key
    return out


def _set_columns(values: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Size of each set and 128 bits that identify it."""
    n, full = np.diff(ends), np.flatnonzero(np.diff(ends))
    f1, f2 = np.zeros(len(n), np.uint64), np.zeros(len(n), np.uint64)
    if len(full):
        f1[full] = np.add.reduceat(mix(values), ends[full])
        f2[full] = np.add.reduceat(mix(values ^ np.uint64(0x5851F42D4C957F2D)), ends[full])
    return n, f1, f2


def _signed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, data, offsets in slices(batches, "text", PIECE):
        values, ends = shingle_sets(data, offsets)
        n, f1, f2 = _set_columns(values, ends)
        full = np.flatnonzero(n)
        keys = sub_keys(values, ends[full]) if len(full) else np.zeros((2 * SUB, 0), np.uint64)
        at = pa.array(np.concatenate([[0], np.cumsum((n > 0) * SUB)]), pa.int32())
        left, right = (pa.ListArray.from_arrays(at, pa.array(as_long(k.T).ravel())) for k in (keys[:SUB], keys[SUB:]))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n), pa.array(as_long(f1)), pa.array(as_long(f2)), left, right], names=["doc_id", "n", "f1", "f2", "left", "right"])


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, data, offsets in slices(batches, "text", PIECE):
        values, ends = shingle_sets(data, offsets)
        n, f1, f2 = _set_columns(values, ends)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n), pa.array(as_long(f1)), pa.array(as_long(f2)), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(as_long(values)))], names=["id", "n", "f1", "f2", "members"])


def _shared(keys: DataFrame) -> DataFrame:
    """(c, keys): for each class the sub-keys of column x that some other class has too."""
    twice = keys.groupBy("x").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("x")
    return keys.join(twice, "x").groupBy("c").agg(F.collect_list("x").alias("keys"))  # SUB keys at most


def _cells(classes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(cell, c): the table keys that can be equal to another class's; and (c, lefts): their first sub-keys."""
    left = store(_shared(classes.select("c", F.explode("left").alias("x"))).withColumnRenamed("keys", "lefts"), "lefts")
    right = _shared(classes.join(left.select("c"), "c").select("c", F.explode("right").alias("x"))).withColumnRenamed("keys", "rights")
    both = left.join(right, "c").select("c", F.explode("lefts").alias("first"), "rights")
    return both.select(F.explode(F.transform("rights", lambda r: F.xxhash64("first", r))).alias("cell"), "c"), left


def _fits(one, two, percent: int):
    return (one * 100 >= two * percent) & (two * 100 >= one * percent)


def _enough(common, one, two, percent: int):
    """Whether sets of sizes one and two with so many common shingles are similar enough."""
    return common * 100 >= (one + two - common) * percent


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose full sets are similar enough."""
    one = sets.select(F.col("c").alias("a"), F.col("members").alias("sa"))
    two = sets.select(F.col("c").alias("b"), F.col("members").alias("sb"))
    same = pairs.join(one, "a").join(two, "b").select("a", "b", F.size(F.array_intersect("sa", "sb")).alias("same"), (F.size("sa") + F.size("sb")).alias("both"))
    return same.where(F.col("same") * 100 >= (F.col("both") - F.col("same")) * percent).select("a", "b")


def _sets_of(source: DataFrame, wanted: DataFrame) -> DataFrame:
    """(c, n, members): the full set of every wanted class (c, n, f1, f2, rep)."""
    kind = source.schema["doc_id"].dataType.simpleString()
    ids = wanted.select(F.col("rep").alias("id")).distinct()
    near = source.withColumnRenamed("doc_id", "id").alias("s").join(small(store(ids, "ids")).alias("i"), F.expr("s.id <=> i.id"), "left_semi")
    sets = near.mapInArrow(_sets, f"id {kind}, n bigint, f1 bigint, f2 bigint, members array<bigint>")
    return store(sets.join(wanted.select("c", "n", "f1", "f2"), ["n", "f1", "f2"]).select("c", "n", "members").dropDuplicates(["c"]), "sets")


def _bounds(sets: DataFrame, percent: int) -> tuple[DataFrame, DataFrame]:
    """Pairs (a, b) that share a shingle of at most RARE of the classes; and (c, n, f, over, b0, b1, ...): size, number of
    the other, frequent shingles, and these by parts of the hash space, of the classes that they alone could link.

    Of k shingles in a part, the first LEVELS set a bit of their level each; over counts the rest.
    """
    each = sets.select("c", "n", F.explode("members").alias("x"))
    held = store(each.groupBy("x").agg(F.count("*").alias("holders")).where("holders > 1"), "held")
    rare = store(each.join(held.where(F.col("holders") <= RARE), "x").select("x", "c", "n"), "rare")
    one, two = rare.alias("one"), rare.alias("two")
    pairs = one.join(two, (F.col("one.x") == F.col("two.x")) & (F.col("one.c") < F.col("two.c")) & _fits(F.col("one.n"), F.col("two.n"), percent))
    pairs = store(pairs.select(F.col("one.c").alias("a"), F.col("two.c").alias("b")).distinct(), "rare-pairs")
    discard(rare)
    often = each.join(held.where(F.col("holders") > RARE).select("x"), "x").groupBy("c", "n", F.pmod("x", F.lit(PARTS)).cast("int").alias("part")).agg(F.count("*").alias("k"))
    often = often.withColumns({"place": F.expr("shiftleft(1L, part % 64)"), "half": F.floor(F.col("part") / 64)})
    bit = lambda w: F.coalesce(F.bit_or(F.when((F.col("half") == w % HALVES) & (F.col("k") > w // HALVES), F.col("place"))), F.lit(0).cast("bigint"))
    over = F.sum(F.greatest(F.col("k") - LEVELS, F.lit(0).cast("bigint")))
    sized = often.groupBy("c", "n").agg(F.sum("k").alias("f"), over.alias("over"), *[bit(w).alias(f"b{w}") for w in range(WORDS)])
    bounds = store(sized.where(_enough(F.col("f"), F.col("n"), F.col("f"), percent)), "bounds")
    discard(held)
    return pairs, bounds


def _several(rows: DataFrame) -> DataFrame:
    """The rows (cell, comp, ...) of cells that hold several components."""
    open_ = rows.groupBy("cell").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").select("cell")
    return rows.join(open_, "cell", "left_semi")


def _centres(rows: DataFrame, width: int) -> DataFrame:
    """The rows with the fewest rare shingles, width for each cell, none of its largest component if width is over 1."""
    if width > 1:
        sizes = rows.groupBy("cell", "comp").agg(F.count("*").alias("size"))
        largest = sizes.groupBy("cell").agg(F.max_by("comp", F.struct("size", "comp")).alias("largest"))
        rows = rows.join(largest, "cell").where("comp <> largest")
    order = F.struct(F.col("n") - F.col("f"), F.xxhash64("c"))
    salt = F.pmod(F.xxhash64("c", F.lit(width)), F.lit(width)).alias("salt")
    return rows.groupBy("cell", salt).agg(F.min_by("c", order).alias("c")).select("cell", "c")


def _proved(rows: DataFrame, comps: DataFrame, bounds: DataFrame, sets: DataFrame, known: list[DataFrame], percent: int) -> list[DataFrame]:
    """Links between the components (c, comp) of open cells, by centres until every pair is ruled out or confirmed."""
    spark, links, width = rows.sparkSession, [], 1
    facts = store(bounds.join(comps, "c", "left").withColumn("comp", F.coalesce("comp", "c")), "facts")
    bits = [F.bit_count(F.col(f"one.b{w}").bitwiseAND(F.col(f"two.b{w}"))) for w in range(WORDS)]
    common = F.least(F.col("one.f"), F.col("two.f"), sum(bits, F.least("one.over", "two.over")))
    able = (F.col("one.comp") != F.col("two.comp")) & (common * (100 + percent) >= (F.col("one.n") + F.col("two.n")) * percent)
    while True:
        sent = small(facts)
        now = store(_several(rows.join(sent.select("c", "n", "f", "comp"), "c")), "open")
        if now.isEmpty():
            return links
        centre = store(_centres(now, width), "centres")
        one, two = (x.select("cell", "c").join(sent, "c").alias(end) for x, end in ((now, "one"), (centre, "two")))
        pairs = one.join(two, (F.col("one.cell") == F.col("two.cell")) & able).select(F.least("one.c", "two.c").alias("a"), F.greatest("one.c", "two.c").alias("b")).distinct()
        pairs = store(pairs.join(read(spark, known), ["a", "b"], "left_anti"), "tested")
        more = store(_confirmed(pairs, sets, percent), "links")
        known, links = [*known, pairs], [*links, more]
        rows = store(now.select("cell", "c").join(centre, ["cell", "c"], "left_anti"), "rows")
        for old in (now, centre):
            discard(old)
        if not more.isEmpty():
            between = more.join(facts.select(F.col("c").alias("a"), F.col("comp").alias("x")), "a").join(facts.select(F.col("c").alias("b"), F.col("comp").alias("y")), "b")
            to = components(between.select("x", "y"), "x", "y").toDF("comp", "to")
            facts = store(facts.join(to, "comp", "left").withColumn("comp", F.coalesce("to", "comp")).drop("to"), "facts")
        width *= GROWTH


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", percent: int = PERCENT) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of docs."""
    spark = docs.sparkSession
    source = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    kind, key = source.schema["doc_id"].dataType.simpleString(), ["n", "f1", "f2"]
    signed = store(source.mapInArrow(_signed, f"doc_id {kind}, n bigint, f1 bigint, f2 bigint, left array<bigint>, right array<bigint>"), "signatures")
    classes = signed.where("n > 0").groupBy(*key).agg(F.min("doc_id").alias("rep"), F.any_value("left").alias("left"), F.any_value("right").alias("right"))
    classes = store(classes.withColumn("c", F.monotonically_increasing_id()), "classes")
    sig = store(signed.select("doc_id", *key), "keys")  # what lies on disk has no sub-keys once they are used
    discard(signed)

    again = sig.where("n > 0").groupBy("doc_id").agg(F.count("*").alias("rows")).where("rows > 1 and doc_id is not null").select("doc_id")
    texts = store(sig.join(small(store(again, "again")), "doc_id").join(classes.select("c", *key), key).select("doc_id", "c").distinct(), "texts")
    own = texts.join(texts.groupBy("doc_id").agg(F.min("c").alias("b")), "doc_id").where("c <> b").select(F.col("c").alias("a"), "b")
    # a star in each cell
    cells, lefts = _cells(classes)
    cells = store(cells, "cells")
    keyed, classes = classes, store(classes.select("c", "rep", *key), "classes")
    discard(keyed)
    centre = cells.groupBy("cell").agg(F.min_by("c", F.xxhash64("c")).alias("centre"))
    pairs = cells.join(centre, "cell").where("c <> centre").select(F.least("c", "centre").alias("a"), F.greatest("c", "centre").alias("b"))
    pairs = store(pairs.distinct(), "pairs")
    discard(cells)
    met = pairs.select(F.explode(F.array("a", "b")).alias("c")).distinct()
    met = store(classes.select("c", "rep", *key).join(met, "c"), "met")
    sets = _sets_of(source, met)
    sizes = small(sets.select("c", "n"))
    sized = pairs.join(sizes.toDF("a", "na"), "a").join(sizes.toDF("b", "nb"), "b")
    tested = store(sized.where(_fits(F.col("na"), F.col("nb"), percent)).select("a", "b"), "tested")
    links = [store(_confirmed(tested, sets, percent), "links"), store(own, "links")]

    # the cells of a first sub-key together, where they hold several components
    comps = store(components(read(spark, links), "a", "b").toDF("c", "comp"), "components")
    label = small(comps)
    rows = lefts.join(small(met.select("c")), "c").join(label, "c", "left")
    rows = store(_several(rows.select(F.explode("lefts").alias("cell"), "c", F.coalesce("comp", "c").alias("comp"))).select("cell", "c"), "rows")
    if not rows.isEmpty():
        rare, bounds = _bounds(sets.join(rows.select("c").distinct(), "c", "left_semi"), percent)
        rare = rare.join(tested, ["a", "b"], "left_anti").join(label.toDF("a", "x"), "a", "left").join(label.toDF("b", "y"), "b", "left")
        rare = store(rare.where(F.coalesce("x", "a") != F.coalesce("y", "b")).select("a", "b"), "tested")
        links.append(store(_confirmed(rare, sets, percent), "links"))
        comps = store(components(read(spark, links), "a", "b").toDF("c", "comp"), "components")
        more = _proved(rows, comps, bounds, sets, [tested, rare], percent)
        if more:
            comps = components(read(spark, [*links, *more]), "a", "b").toDF("c", "comp")
    for old in (pairs, lefts, met, sets):
        discard(old)

    # the smallest id of each component
    named = classes.select("c", "rep", *key).join(comps, "c", "left").withColumn("comp", F.coalesce("comp", "c"))
    first = named.groupBy("comp").agg(F.min("rep").alias("component_id"))
    named = named.join(first, "comp").select(*key, "component_id")
    out = sig.select("doc_id", *key).join(named, key, "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def op5_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir))


def brute_force(texts: dict[int, str | None], percent: int = PERCENT) -> dict[int, tuple[int, int]]:
    """(n_shingles, component_id) of each document by comparing all pairs that share a shingle, for tests."""
    import re

    sets = {}
    for i, t in texts.items():
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
        sets[i] = {tuple(w[j : j + SHINGLE]) for j in range(len(w) - SHINGLE + 1)} if len(w) >= SHINGLE else ({tuple(w)} if w else set())
    up = {i: i for i in texts}

    def top(i: int) -> int:
        while up[i] != i:
            i = up[i]
        return i

    holders: dict[tuple, list[int]] = {}
    for i, s in sets.items():
        for x in s:
            holders.setdefault(x, []).append(i)
    near = {(a, b) for h in holders.values() for k, a in enumerate(h) for b in h[k + 1 :]}
    for a, b in near:
        same = len(sets[a] & sets[b])
        if 100 * same >= percent * (len(sets[a]) + len(sets[b]) - same):
            a, b = sorted((top(a), top(b)))
            up[b] = a
    return {i: (len(sets[i]), top(i)) for i in texts}
