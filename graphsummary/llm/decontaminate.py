"""Benchmark decontamination by template canonicalisation.

Texts become template tokens: numbers, names and units turn into typed placeholders (neighbouring numbers or names of a
sentence make one), other words are lower-cased. Windows of template tokens of the documents are joined with those of the
benchmark by hash. Matches of a document and an item on one alignment are put together; the pair is reported if they cover
COVER tokens or the whole of a shorter item, and the slots are consistent: each value of the item has one value in the
document, where different values may become equal. So a question is also found after its numbers and names were changed
throughout.

A token is a run of letters and digits. A number starts with a digit. A unit is one of UNITS after a number. A name
starts with a capital, also where it opens a sentence: whether an opening word is a name cannot be told, and a word that
is none has the same value on both sides. Windows with fewer than LITERALS plain words (of a whole shorter item: SHORT)
are too common to find anything by: they count only on an alignment that another window has found.

Beside the templates stand literal windows: of case-folded words as they are, and of single code points in scripts without
spaces. An item whose literal windows all stand in a document on one alignment is reported, whatever it is made of. Where
fewer than COVER + 1 - WINDOW of an item's template windows have LITERALS plain words, COVER literal tokens are enough
(POINTS if most of the tokens are single code points); so they are for all items of single code points.

Null and empty texts match nothing. Rows that share a doc_id are one document; a null doc_id is a document too. Repeated
items are reported for each item_id. An empty table on either side gives no rows. Other columns are left out, whatever
their names. A text is turned into arrays whole, about 30 bytes for each of its own; it is never cut.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm.common import as_long, documents, hash_runs, lowered, mix, runs, slices, small, store

WINDOW, LITERALS, SHORT, COVER, POINTS = 8, 3, 5, 13, 26
#: Kinds of windows: templates with and without enough plain words, literal ones.
DENSE, SPARSE, LITERAL = 0, 1, 2
#: Bits of the filter of benchmark windows that documents are read against; its size does not depend on the data.
FILTER_BITS = 1 << 24
#: Bytes of text that become arrays at once: about 60 bytes of them for each of the text's.
PIECE = 1 << 19
# fixed values: words that are units after a number
UNITS = "mm cm m km in ft yd mi mg g kg t lb oz ml cl l s sec min h hr hrs day days week weeks month months year years hour hours minute minutes second seconds usd eur gbp dollar dollars euro euros cent cents percent pct kb mb gb tb hz khz mhz ghz w kw mw v a k c f mph kmh".split()

_WORD = np.zeros(256, bool)
_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
_STOP = np.zeros(256, bool)
_STOP[[ord(c) for c in ".!?\n"]] = True
_MULT = (np.random.default_rng(77).integers(0, 1 << 62, (WINDOW,)) * 2 + 1).astype(np.uint64)
_NUM, _NAME, _UNIT = np.uint64(0xA0761D6478BD642F), np.uint64(0xE7037ED1A0B428DB), np.uint64(0x8EBC6AF09C88C6E3)
_LITERAL = np.uint64(0x589965CC75374CC3)
_UNIT_HASHES = np.sort(hash_runs(np.frombuffer("".join(UNITS).encode(), np.uint8), np.array([len(u) for u in UNITS])))

#: Code points up to the supplementary ideographs, which are all alike: 0 parts tokens, 1 is in a word, 2 is a token itself.
_POINTS = 0x20001
_UNSPACED = [(0x0E00, 0x0FFF), (0x1000, 0x109F), (0x1780, 0x17FF), (0x1950, 0x19DF), (0x1A20, 0x1AAF), (0x2E80, 0x30FF), (0x31F0, 0x31FF), (0x3400, 0x4DBF), (0x4E00, 0xA4CF), (0xA9E0, 0xA9FF), (0xAA60, 0xAADF), (0xF900, 0xFAFF), (0xFF66, 0xFF9F), (0x1B000, 0x1B16F), (0x20000, 0x20000)]
_KIND = np.array([unicodedata.category(chr(c))[0] in "LMN" for c in range(_POINTS)], np.uint8)
for _low, _high in _UNSPACED:
    _KIND[_low : _high + 1] *= 2
_FOLD = np.array([ord(x) if len(x := chr(c).lower()) == 1 else c for c in range(_POINTS)], np.uint32)


def literals(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of case-folded words and single code points, which are single code points, and each text's offsets among them."""
    lead = np.flatnonzero((data & 0xC0) != 0x80)
    point = data[lead].astype(np.uint32)
    wide = np.flatnonzero(point >= 0x80)
    if len(wide):
        rest = np.concatenate([data, np.zeros(3, np.uint8)])
        a, b, c, d = point[wide], *(rest[lead[wide] + j].astype(np.uint32) & 0x3F for j in (1, 2, 3))
        point[wide] = np.where(a < 0xE0, (a & 0x1F) << 6 | b, np.where(a < 0xF0, (a & 0x0F) << 12 | b << 6 | c, (a & 0x07) << 18 | b << 12 | c << 6 | d))
    row = np.minimum(point, _POINTS - 1)
    kind, point = _KIND[row], np.where(point < _POINTS, _FOLD[row], point)
    texts = np.searchsorted(lead, offsets)
    start = kind == 1
    start[1:] &= kind[:-1] != 1
    head = texts[:-1][texts[:-1] < len(kind)]
    start[head] = kind[head] == 1
    start |= kind == 2
    at = np.concatenate([[0], np.cumsum(start)])[texts]
    solid = kind > 0
    begin = np.flatnonzero(start[solid])
    if not len(begin):
        return np.zeros(0, np.uint64), np.zeros(0, bool), at
    point = point[solid].astype(np.uint64)
    place = np.arange(len(point)) - np.repeat(begin, np.diff([*begin, len(point)]))
    return mix(np.add.reduceat(mix((place.astype(np.uint64) << np.uint64(32) | point) * _LITERAL + _NUM), begin)), kind[start] == 2, at


def templates(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Template tokens, slot values, which are slots, and each text's offsets among them."""
    solid = _WORD[data]
    starts, lens, at = runs(solid, offsets)
    n = len(starts)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, bool), at
    word = hash_runs(lowered(data[solid]), lens)
    first, second = data[starts], data[np.minimum(starts + 1, len(data) - 1)]
    stops = np.concatenate([[0], np.cumsum(_STOP[data])])
    opens = np.ones(n, bool)  # begins a sentence or a text
    opens[1:] = stops[starts[1:]] > stops[starts[:-1] + lens[:-1]]
    head = np.zeros(n, bool)
    head[at[:-1][at[:-1] < n]] = True
    opens |= head
    number = (first >= 48) & (first <= 57)
    upper = (first >= 65) & (first <= 90) | (first == 0xC3) & (second >= 0x80) & (second <= 0x9E)
    name = upper.copy()
    after_number = np.zeros(n, bool)
    after_number[1:] = number[:-1] & ~head[1:]
    unit = after_number & (_UNIT_HASHES[np.minimum(np.searchsorted(_UNIT_HASHES, word), len(_UNIT_HASHES) - 1)] == word)
    name &= ~unit
    joins = np.zeros(n, bool)
    joins[1:] = ~head[1:] & (number[1:] & number[:-1] | name[1:] & name[:-1] & ~opens[1:])
    begin = np.flatnonzero(~joins)
    value = np.add.reduceat(word * (np.arange(n, dtype=np.uint64) - np.repeat(begin, np.diff([*begin, n])).astype(np.uint64) + np.uint64(1)), begin)
    token = np.where(number, _NUM, np.where(name, _NAME, np.where(unit, _UNIT, word)))[begin]
    slot = (number | name | unit)[begin]
    return token, mix(value ^ token), slot, np.searchsorted(begin, at)


def windows(token: np.ndarray, slot: np.ndarray | None, at: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hash, text, start (among all tokens) and kind of every window of the length; literal ones if no slots are given."""
    m = len(token) - length + 1
    if m <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int8)
    h = np.full(m, np.uint64(length) if slot is not None else _LITERAL + np.uint64(length), np.uint64)
    for j in range(length):
        h += token[j : m + j] * _MULT[j]
    owner = np.repeat(np.arange(len(at) - 1), np.diff(at))[:m]
    start = np.flatnonzero(np.arange(m) + length <= at[owner + 1])
    kind = np.full(len(start), LITERAL, np.int8)
    if slot is not None:
        plain = np.concatenate([[0], np.cumsum(~slot)])
        kind = np.where(plain[start + length] - plain[start] >= (LITERALS if length == WINDOW else SHORT), DENSE, SPARSE).astype(np.int8)
    return mix(h[start]), owner[start], start, kind


def _rows(ids: pa.Array, of: np.ndarray, h: np.ndarray, start: np.ndarray, kind: np.ndarray, length: int, token_at: np.ndarray, value: np.ndarray | None, slot: np.ndarray | None, names: list[str]) -> pa.RecordBatch:
    """Window rows: id, hash, position in its text, the slot values in the window, and its kind."""
    spans = [value[s : s + length][slot[s : s + length]] for s in start] if value is not None else []
    ends = np.concatenate([[0], np.cumsum([len(x) for x in spans])]).astype(np.int32) if spans else np.zeros(len(h) + 1, np.int32)
    flat = np.concatenate(spans) if spans else np.zeros(0, np.uint64)
    return pa.RecordBatch.from_arrays([ids.take(pa.array(of)), pa.array(as_long(h)), pa.array((start - token_at[of]).astype(np.int32)), pa.ListArray.from_arrays(pa.array(ends), pa.array(as_long(flat))), pa.array(kind.astype(np.int32))], names=names)


_ITEM = ["item_id", "h", "item_at", "item_slots", "kind", "length", "points"]


def _item_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, data, offsets in slices(batches, "text", PIECE):
        token, value, slot, at = templates(data, offsets)
        literal, single, literal_at = literals(data, offsets)
        singles = np.concatenate([[0], np.cumsum(single)])[literal_at]
        points = 2 * np.diff(singles) > np.diff(literal_at)
        for tokens, slots, values, first in ((token, slot, value, at), (literal, None, None, literal_at)):
            n = np.diff(first)
            for length in sorted({min(WINDOW, int(k)) for k in n if k}):
                h, of, start, kind = windows(tokens, slots, first, length)
                own = n[of] >= WINDOW if length == WINDOW else n[of] == length
                h, of, start, kind = h[own], of[own], start[own], kind[own]
                if len(h):
                    rows = _rows(batch.column(0), of, h, start, kind, length, first, values, slots, _ITEM[:5])
                    yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(np.full(len(h), length, np.int32)), pa.array(points[of])], names=_ITEM)


def _doc_windows(held):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits, lengths = held.value
        for batch, data, offsets in slices(batches, "text", PIECE):
            token, value, slot, at = templates(data, offsets)
            literal, _, literal_at = literals(data, offsets)
            for length, is_literal in lengths:
                tokens, slots, values, first = (literal, None, None, literal_at) if is_literal else (token, slot, value, at)
                h, of, start, kind = windows(tokens, slots, first, length)
                place = (h % np.uint64(FILTER_BITS)).astype(np.int64)
                hit = np.flatnonzero((bits[place >> 3] >> (place & 7).astype(np.uint8)) & 1 == 1)
                if is_literal and length < WINDOW:  # a whole item: one of its places is enough
                    hit = hit[np.sort(np.unique(np.stack([of[hit].astype(np.uint64), h[hit]]), axis=1, return_index=True)[1])]
                if len(hit):
                    yield _rows(batch.column(0), of[hit], h[hit], start[hit], kind[hit], length, first, values, slots, ["doc_id", "h", "doc_at", "doc_slots", "kind"])

    return run


def matches(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """(doc_id, item_id, n_windows, item_windows, n_slots) for every document and item that match; literal windows and no slots for those that only they have found."""
    source = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    bench = benchmark.select(F.col(item_id).alias("item_id"), F.col(item_text).alias("text"))
    doc_kind, item_kind = source.schema["doc_id"].dataType.simpleString(), bench.schema["item_id"].dataType.simpleString()
    items = store(bench.mapInArrow(_item_windows, f"item_id {item_kind}, h bigint, item_at int, item_slots array<bigint>, kind int, length int, points boolean"), "items")
    lengths = sorted((r[0], r[1]) for r in items.select("length", F.col("kind") == LITERAL).distinct().collect())  # 2 * WINDOW at most
    place = F.pmod("h", F.lit(FILTER_BITS))  # FILTER_BITS divides 2 ** 64: signed and unsigned remainders agree
    bits = np.zeros(FILTER_BITS // 8, np.uint8)
    for r in items.select(F.floor(place / 8).alias("byte"), F.call_function("shiftleft", F.lit(1), (place % 8).cast("int")).alias("bit")).groupBy("byte").agg(F.bit_or("bit").alias("bit")).toArrow().to_batches():
        bits[r.column(0).to_numpy()] = r.column(1).to_numpy()
    held = docs.sparkSession.sparkContext.broadcast((bits, lengths))
    found = store(source.where("text is not null").mapInArrow(_doc_windows(held), f"doc_id {doc_kind}, h bigint, doc_at int, doc_slots array<bigint>, kind int"), "found")
    of = lambda df, kind: df.where(F.col("kind") == kind).drop("kind")
    shift = (F.col("doc_at") - F.col("item_at")).alias("shift")
    columns = ["doc_id", "item_id", "shift", "item_at", "length", F.arrays_zip(F.col("item_slots").alias("i"), F.col("doc_slots").alias("d")).alias("slots")]
    dense = of(found, DENSE).join(small(of(items, DENSE)), "h").where(F.size("doc_slots") == F.size("item_slots")).withColumn("shift", shift).select(*columns)
    # windows with few plain words, on the alignments that the others have found
    lines = dense.select("doc_id", "item_id", "shift", "length").distinct().join(small(of(items, SPARSE)), ["item_id", "length"]).withColumn("doc_at", F.col("shift") + F.col("item_at"))
    sparse = lines.alias("l").join(of(found, SPARSE).alias("f"), F.expr("l.doc_id <=> f.doc_id and l.h = f.h and l.doc_at = f.doc_at")).select("l.*", "f.doc_slots").where(F.size("doc_slots") == F.size("item_slots")).select(*columns)
    lined = dense.unionByName(sparse).groupBy("doc_id", "item_id", "shift").agg(F.countDistinct("item_at").alias("n_windows"), F.max("length").alias("length"), F.array_distinct(F.flatten(F.collect_list("slots"))).alias("slots"))
    lined = lined.where(F.size(F.array_distinct(F.transform("slots", lambda s: s["i"]))) == F.size("slots"))
    number = lambda *kinds: F.countDistinct(F.when(F.col("kind").isin(*kinds), F.col("item_at")))
    whole = small(store(items.groupBy("item_id").agg(number(DENSE, SPARSE).alias("item_windows"), number(DENSE).alias("item_dense"), number(LITERAL).alias("item_literals"), F.max("points").alias("points")), "whole"))
    enough = F.col("n_windows") >= F.greatest(F.lit(1), F.least(F.col("item_windows"), F.lit(COVER + 1) - F.col("length")))
    by_template = lined.join(whole, "item_id").where(enough).select("doc_id", "item_id", F.struct(F.lit(1).alias("template"), "n_windows", "item_windows", F.size("slots").alias("n_slots")).alias("m"))
    literal = of(found, LITERAL).join(small(of(items, LITERAL)), "h").select("doc_id", "item_id", shift, "item_at", "length")
    literal = literal.groupBy("doc_id", "item_id", "shift").agg(F.countDistinct("item_at").alias("n_windows"))
    part = F.when(F.col("points"), POINTS + 1 - WINDOW).when(F.col("item_dense") <= COVER - WINDOW, COVER + 1 - WINDOW)
    enough = F.col("n_windows") >= F.least("item_literals", part)  # least() passes over null: the whole item
    by_words = literal.join(whole, "item_id").where(enough).select("doc_id", "item_id", F.struct(F.lit(0).alias("template"), "n_windows", F.col("item_literals").alias("item_windows"), F.lit(0).alias("n_slots")).alias("m"))
    best = by_template.unionByName(by_words).groupBy("doc_id", "item_id").agg(F.max("m").alias("m"))
    return best.select("doc_id", "item_id", "m.n_windows", "m.item_windows", "m.n_slots")


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return matches(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
