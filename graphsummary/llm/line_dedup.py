"""Reversible line dedup: exact reference counts of line keys, with sharded cuckoo filters of the frequent ones.

The reference table holds for every line key the number of documents that contain it. Keys in at least `least`
documents are frequent; their 16-bit fingerprints are in cuckoo filters, one per shard of keys. Adding or deleting
documents adds to or takes from the table, and inserts into or deletes from the filters just the keys that cross the
threshold; a shard's filter that is full is built anew, larger, from the table, and with many more frequent keys all are
dealt to more shards. Applied to any documents, the keys that pass a filter are looked up in the table, and those that
are not frequent are sent along, so the lines that are dropped are exactly those of the table. Where filters or wrong keys
are too large to send, lines meet the table in a join, but for the HOT most frequent keys, which are sent: no line that
stands nearly everywhere meets in one task. Both ways give the same rows.

A key is 128 bits of XXH3 of the stripped, lower-cased line. Null and empty texts have one empty line, which is never
frequent. Repeated rows count as separate documents. An empty table gives no rows. A very long text is split whole in one
worker. Columns of docs named n_lines and n_dropped are replaced; all others stay.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm.common import buffers, documents, store

SPACE = b" \t\n\x0b\x0c\r"
SLOTS, KICKS = 4, 500
#: Frequent keys for each shard, and the most bytes of filters that are sent to every executor.
SHARD_KEYS, SENT_BYTES = 50_000, 64 << 20
#: The most frequent keys that are sent to every executor where the others meet the table in a join.
HOT = 100_000


def line_keys(raw: bytes, least_chars: int) -> tuple[list[bytes], list[bytes]]:
    """Lines, and the 16-byte key of each; empty where the key has fewer than least_chars code points."""
    import xxhash

    lines = raw.split(b"\n")
    keys = []
    for line in lines:
        key = line.strip(SPACE).lower()
        enough = len(key) >= least_chars and (least_chars <= 1 or len(key.decode("utf-8", "replace")) >= least_chars)
        keys.append(xxhash.xxh3_128_digest(key) if enough and key else b"")
    return lines, keys


def as_pairs(keys: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(keys), np.int64).reshape(-1, 2)


class Cuckoo:
    """A cuckoo filter over (k1, k2) keys: 16-bit fingerprints, four to a bucket. A key is inserted once."""

    def __init__(self, table: np.ndarray):
        self.table = table

    @classmethod
    def sized(cls, keys: int) -> Cuckoo:
        buckets = 1 << max(2, int(np.ceil(np.log2(max(1, keys) / SLOTS / 0.84))))
        return cls(np.zeros((buckets, SLOTS), np.uint16))

    @classmethod
    def loads(cls, raw: bytes) -> Cuckoo:
        return cls(np.frombuffer(raw, np.uint16).reshape(-1, SLOTS).copy())

    def dumps(self) -> bytes:
        return self.table.tobytes()

    def places(self, k: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        mask = len(self.table) - 1
        mark = np.maximum((k[:, 1] & 0xFFFF), 1).astype(np.uint16)
        one = (k[:, 0] >> 20) & mask
        return mark, one, one ^ self.turn(mark, mask)

    @staticmethod
    def turn(mark: np.ndarray, mask: int) -> np.ndarray:
        return ((mark.astype(np.int64) * 0x5BD1E995) >> 7) & mask

    def has(self, k: np.ndarray) -> np.ndarray:
        if not len(k):
            return np.zeros(0, bool)
        mark, one, two = self.places(k)
        return (self.table[one] == mark[:, None]).any(1) | (self.table[two] == mark[:, None]).any(1)

    def insert(self, k: np.ndarray) -> bool:
        """False when a fingerprint finds no place; then the filter has to be built larger."""
        mask, rng = len(self.table) - 1, np.random.default_rng(5)
        for mark, one, two in zip(*self.places(k), strict=True):
            at = one if (self.table[one] == 0).any() else two
            for _ in range(KICKS):
                free = np.flatnonzero(self.table[at] == 0)
                if len(free):
                    self.table[at, free[0]] = mark
                    break
                j = int(rng.integers(SLOTS))
                mark, self.table[at, j] = self.table[at, j], mark
                at ^= int(self.turn(np.array([mark]), mask)[0])
            else:
                return False
        return True

    def delete(self, k: np.ndarray) -> None:
        for mark, one, two in zip(*self.places(k), strict=True):
            for at in (one, two):
                j = np.flatnonzero(self.table[at] == mark)
                if len(j):
                    self.table[at, j[0]] = 0
                    break


def build(keys: np.ndarray, room: int = 0) -> Cuckoo:
    size = max(len(keys), room)
    while True:
        made = Cuckoo.sized(size)
        if made.insert(keys):
            return made
        size *= 2


def reference_counts(docs: DataFrame, text: str = "text", least_chars: int = 1) -> DataFrame:
    """(k1, k2, docs): in how many rows of docs each line key stands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = buffers(batch.column(0))
            raw, keys = data.tobytes(), []
            for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
                keys += {k for k in line_keys(raw[a:b], least_chars)[1] if k}
            if keys:
                pairs, n = np.unique(as_pairs(keys), axis=0, return_counts=True) if len(keys) > 1 else (as_pairs(keys), np.ones(1, np.int64))
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1]), pa.array(n.astype(np.int64))], names=["k1", "k2", "docs"])

    return docs.select(text).mapInArrow(run, "k1 bigint, k2 bigint, docs bigint").groupBy("k1", "k2").agg(F.sum("docs").alias("docs"))


@dataclass
class LineIndex:
    """refs: (k1, k2, docs), stored. filters: (shard, bits), stored. Documents can be added and deleted."""

    refs: DataFrame
    filters: DataFrame
    shards: int
    least: int
    least_chars: int

    @classmethod
    def of(cls, docs: DataFrame, text: str = "text", least: int = 10, least_chars: int = 1) -> LineIndex:
        refs = store(reference_counts(docs, text, least_chars), "refs")
        return cls._dealt(refs, least, least_chars)

    @classmethod
    def _dealt(cls, refs: DataFrame, least: int, least_chars: int) -> LineIndex:
        """The index of a table, with as many shards as its frequent keys need."""
        shards = max(1, -(-refs.where(F.col("docs") >= least).count() // SHARD_KEYS))
        return cls(refs, store(_filters(refs, least, shards), "filters"), shards, least, least_chars)

    def changed(self, docs: DataFrame, text: str = "text", sign: int = 1) -> LineIndex:
        """The index after adding (sign 1) or deleting (sign -1) documents."""
        delta = reference_counts(docs, text, self.least_chars).withColumn("docs", F.col("docs") * sign)
        least, shards = self.least, self.shards
        both = self.refs.withColumnRenamed("docs", "old").join(delta, ["k1", "k2"], "full").select("k1", "k2", F.coalesce("old", F.lit(0)).alias("old"), (F.coalesce("old", F.lit(0)) + F.coalesce("docs", F.lit(0))).alias("docs"))
        both = store(both, "changed")
        refs = store(both.where("docs > 0").select("k1", "k2", "docs"), "refs")
        if refs.where(F.col("docs") >= least).count() > 2 * SHARD_KEYS * shards:
            return self._dealt(refs, least, self.least_chars)
        moved = both.where((F.col("old") >= least) != (F.col("docs") >= least)).select(F.pmod("k1", F.lit(shards)).cast("int").alias("shard"), "k1", "k2", (F.col("docs") >= least).alias("add"))
        made = store(self.filters.groupBy("shard").cogroup(moved.groupBy("shard")).applyInPandas(_update_shard, "shard int, bits binary"), "filters")
        full = [r["shard"] for r in made.where("bits is null").select("shard").collect()]  # of the shards, not the keys
        if full:
            made = store(made.where("bits is not null").union(_filters(refs, least, shards, full)), "filters")
        return LineIndex(refs, made, shards, least, self.least_chars)

    def add(self, docs: DataFrame, text: str = "text") -> LineIndex:
        return self.changed(docs, text, 1)

    def delete(self, docs: DataFrame, text: str = "text") -> LineIndex:
        return self.changed(docs, text, -1)

    def apply(self, docs: DataFrame, text: str = "text") -> DataFrame:
        """docs with frequent lines taken out of text, plus n_lines and n_dropped; every column stays."""
        docs = docs.drop("n_lines", "n_dropped")
        size = self.filters.agg(F.sum(F.octet_length("bits"))).first()[0] or 0
        if size > SENT_BYTES:
            return self._apply_by_join(docs, text)
        held = self._sent()
        passed = docs.select(text).mapInArrow(_passing(held, self.least_chars), "k1 bigint, k2 bigint").distinct()
        wrong = store(passed.join(self.refs.where(F.col("docs") >= self.least), ["k1", "k2"], "left_anti"), "passing")
        if wrong.count() > SENT_BYTES // 64:
            return self._apply_by_join(docs, text)
        exact = docs.sparkSession.sparkContext.broadcast({np.array([r[0], r[1]], np.int64).tobytes() for r in wrong.collect()})
        return _drop_lines(docs, text, held, exact, self.least_chars)

    def _sent(self):
        return self.refs.sparkSession.sparkContext.broadcast((self.shards, {r["shard"]: bytes(r["bits"]) for r in self.filters.collect()}))

    def _apply_by_join(self, docs: DataFrame, text: str) -> DataFrame:
        """Where filters are too large to send: lines meet the frequent keys in a join, the HOT most frequent ones a sent set."""
        rows = store(docs.withColumn("__row", F.expr("uuid()")), "rows")
        lines = store(rows.select("__row", text).mapInArrow(_line_rows(self.least_chars), "row string, at int, k1 bigint, k2 bigint"), "lines")
        frequent = self.refs.where(F.col("docs") >= self.least)
        hot = F.broadcast(store(frequent.orderBy(F.desc("docs"), "k1", "k2").limit(HOT).select("k1", "k2"), "hot"))
        cold = lines.join(hot, ["k1", "k2"], "left_anti").join(frequent.join(hot, ["k1", "k2"], "left_anti"), ["k1", "k2"], "left_semi")
        hits = lines.join(hot, ["k1", "k2"], "left_semi").union(cold).groupBy("row").agg(F.collect_list("at").alias("__drop"))
        both = rows.join(hits, F.col("__row") == F.col("row"), "left").drop("row")
        lines_of = F.split(F.coalesce(F.col(text), F.lit("")), "\n")
        gone = F.coalesce("__drop", F.array().cast("array<int>"))
        left = F.filter(F.transform(lines_of, lambda x, i: F.struct(x.alias("x"), i.alias("i"))), lambda s: ~F.array_contains(gone, s["i"]))
        made = both.withColumns({"n_lines": F.size(lines_of).cast("bigint"), "n_dropped": F.size(gone).cast("bigint"), text: F.when(F.size(gone) == 0, F.col(text)).otherwise(F.array_join(F.transform(left, lambda s: s["x"]), "\n"))})
        return made.drop("__row", "__drop")


def _filters(refs: DataFrame, least: int, shards: int, only: list[int] | None = None) -> DataFrame:
    """(shard, bits): the filters of the table's frequent keys, of all shards or some."""
    keys = refs.where(F.col("docs") >= least).withColumn("shard", F.pmod("k1", F.lit(shards)).cast("int"))
    return (keys if only is None else keys.where(F.col("shard").isin(only))).groupBy("shard").applyInPandas(_build_shard, "shard int, bits binary")


def _build_shard(pdf: pd.DataFrame) -> pd.DataFrame:
    made = build(pdf[["k1", "k2"]].to_numpy(np.int64), room=1024)
    return pd.DataFrame({"shard": [int(pdf["shard"].iloc[0])], "bits": [made.dumps()]})


def _update_shard(old: pd.DataFrame, moved: pd.DataFrame) -> pd.DataFrame:
    k, add = moved[["k1", "k2"]].to_numpy(np.int64), moved["add"].to_numpy(bool)
    if not len(old):
        return pd.DataFrame({"shard": [int(moved["shard"].iloc[0])], "bits": [build(k[add], room=1024).dumps()]})
    held = Cuckoo.loads(old["bits"].iloc[0])
    held.delete(k[~add])
    done = held.insert(k[add])  # a full filter is left out here and built anew
    return pd.DataFrame({"shard": [int(old["shard"].iloc[0])], "bits": [held.dumps() if done else None]})


def _lookup(sent: tuple[int, dict]):
    shards, raw = sent
    filters = {s: Cuckoo.loads(b) for s, b in raw.items()}

    def has(pairs: np.ndarray) -> np.ndarray:
        out, shard = np.zeros(len(pairs), bool), np.mod(pairs[:, 0], shards)
        for s, f in filters.items():
            mine = np.flatnonzero(shard == s)
            out[mine] = f.has(pairs[mine])
        return out

    return has


def _passing(held, least_chars: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        has = _lookup(held.value)
        for batch in batches:
            data, offsets = buffers(batch.column(0))
            raw = data.tobytes()
            keys = list({k for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True) for k in line_keys(raw[a:b], least_chars)[1] if k})
            pairs = as_pairs(keys)
            hit = pairs[has(pairs)]
            yield pa.RecordBatch.from_arrays([pa.array(hit[:, 0]), pa.array(hit[:, 1])], names=["k1", "k2"])

    return run


def _line_rows(least_chars: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = buffers(batch.column(1))
            raw = data.tobytes()
            for row, a, b in zip(batch.column(0).to_pylist(), offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
                keys = [(i, k) for i, k in enumerate(line_keys(raw[a:b], least_chars)[1]) if k]
                if keys:
                    pairs = as_pairs([k for _, k in keys])
                    yield pa.RecordBatch.from_arrays([pa.array([row] * len(keys)), pa.array([i for i, _ in keys], pa.int32()), pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["row", "at", "k1", "k2"])

    return run


def _drop_lines(docs: DataFrame, text: str, held, exact, least_chars: int) -> DataFrame:
    names = docs.columns
    source = docs
    at = names.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        has, wrong = _lookup(held.value), exact.value
        for whole in batches:
            for lo in range(0, whole.num_rows, 1000):
                batch = whole.slice(lo, 1000)
                data, offsets = buffers(batch.column(at))
                raw, ends = data.tobytes(), offsets.tolist()
                split = [line_keys(raw[a:b], least_chars) for a, b in zip(ends[:-1], ends[1:], strict=True)]
                keys = [k for _, own in split for k in own if k]
                hit = {k for k, h in zip(keys, has(as_pairs(keys)), strict=True) if h and k not in wrong} if keys else set()
                texts, total, dropped = [], [], []
                for (lines, own), null in zip(split, batch.column(at).is_null().to_pylist(), strict=True):
                    left = [x for x, k in zip(lines, own, strict=True) if k not in hit]
                    total.append(len(lines))
                    dropped.append(len(lines) - len(left))
                    texts.append(None if null else b"\n".join(left))
                columns = batch.columns
                columns[at] = pa.array(texts, pa.binary()).cast(batch.column(at).type)
                yield pa.RecordBatch.from_arrays([*columns, pa.array(total, pa.int64()), pa.array(dropped, pa.int64())], names=[*names, "n_lines", "n_dropped"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema)
    return source.mapInArrow(run, f"{kinds}, n_lines bigint, n_dropped bigint")


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    kept = LineIndex.of(docs).apply(docs)
    return kept.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("kept_sha256"))


OP9_SQL = r"""
with lines as (
  select doc_id, text, unnest(string_split(coalesce(text, ''), chr(10))) as line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) as line_no
  from documents),
keyed as (
  select *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key
  from lines),
frequent as (select key from keyed where length(key) >= 1 group by key having count(distinct doc_id) >= 10)
select doc_id, count(*) as n_lines, count(*) filter (where f.key is not null) as n_dropped,
       sha256(coalesce(string_agg(line, chr(10) order by line_no) filter (where f.key is null), '')) as kept_sha256
from keyed left join frequent f on keyed.key = f.key
group by doc_id
"""
