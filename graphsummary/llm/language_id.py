"""Language identification with language-bitmask n-gram filters.

A filter is an array of slots, each a mask with a bit for every language. An n-gram's languages are the AND of the masks
at its slots: one probe answers for all languages together, as a row of Bloom filters laid out by bits would. For a text,
each language's bits are counted over all n-grams, corrected for the rate at which that language's filter answers
falsely; the largest count decides.

N-grams are the 4-byte windows of the UTF-8 text, A-Z lower-cased, runs of ASCII non-letters made one space. An n-gram
belongs to a language if it is at least SHARE as frequent there as in the language where it is most frequent, and makes
LEAST_RATE of the language's n-grams (LEAST of them in a small corpus): noise stays out at any size, and a language has
1 / LEAST_RATE n-grams at most. The number of slots follows from the n-grams of the largest language, so that no language
answers falsely more often than FALSE_RATE. Languages beyond LANGUAGES have further masks for each slot; masks that
together take more than SHARD_BYTES are asked in turn.

A text that is null or has no letter is `und` with score 0, and so is every text if nothing was learned. Ties, and texts too
short for an n-gram, go to the first language by name. Repeated rows are judged alike, an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm.common import documents, fold_of, mix, slices, store

GRAM, PROBES = 4, 3
#: Text for each pass over the arrays, which take about a hundred times as many bytes.
PIECE = 1 << 18
#: The fewest slots of the filter, languages of a mask, and what makes an n-gram part of a language.
SLOTS, LANGUAGES, SHARE, LEAST, LEAST_RATE = 1 << 20, 63, 0.1, 2, 1e-6
#: The rate at which a language may answer falsely; bytes of masks that a worker holds at once; slots read at once.
FALSE_RATE, SHARD_BYTES, READ = 0.01, 256 << 20, 1 << 20
NONE = "und"

_PLAIN = np.full(256, 32, np.uint8)
_PLAIN[65:91] = np.arange(97, 123)
_PLAIN[97:123] = np.arange(97, 123)
_PLAIN[128:] = np.arange(128, 256)


def grams(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All windows of every text as 32-bit values, and each text's offsets among them."""
    n = len(offsets) - 1
    at = offsets[:-1] + np.arange(n)  # room for a space before each text and one after the last
    out = np.full(len(data) + n + 1, 32, np.uint8)
    place = np.ones(len(out), bool)
    place[at] = False
    place[-1] = False
    out[place] = _PLAIN[data]
    keep = np.ones(len(out), bool)
    keep[1:] = (out[1:] != 32) | (out[:-1] != 32)
    keep[at] = True
    first = np.concatenate([[0], np.cumsum(keep)])[np.concatenate([at, [len(out) - 1]])]
    out = out[keep].astype(np.uint32)
    if len(out) < GRAM:
        return np.zeros(0, np.uint32), np.zeros(n + 1, np.int64)
    value = out[: len(out) - 3] << 24 | out[1 : len(out) - 2] << 16 | out[2 : len(out) - 1] << 8 | out[3:]
    # a window belongs to the text in which it starts; those that reach over the next text's space are dropped
    start = np.arange(len(value))
    own = np.searchsorted(first, start, "right") - 1
    inside = start + GRAM - 1 <= first[np.minimum(own + 1, n)]
    value = value[inside]
    return value, np.searchsorted(start[inside], np.minimum(first, len(start)))


def slots(value: np.ndarray, n: int) -> list[np.ndarray]:
    h = [mix((value.astype(np.uint64) << np.uint64(1) | np.uint64(j)) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(1)) for j in range(2)]
    return [((h[0] if j == 0 else h[0] >> np.uint64(32) if j == 1 else h[1]) % np.uint64(n)).astype(np.int64) for j in range(PROBES)]


def slots_for(n: int) -> int:
    """A power of two with room for n n-grams of one language at FALSE_RATE."""
    need = -PROBES * n / np.log(1 - FALSE_RATE ** (1 / PROBES))
    return max(SLOTS, 1 << int(np.ceil(np.log2(max(need, 1)))))


@dataclass
class Model:
    languages: list[str]
    masks: np.ndarray  # a row for each LANGUAGES languages, a mask for each slot

    @property
    def false_rates(self) -> np.ndarray:
        bits = [((self.masks[i // LANGUAGES] >> np.uint64(i % LANGUAGES)) & np.uint64(1)).mean() for i in range(len(self.languages))]
        return np.array(bits) ** PROBES


def gram_counts(docs: DataFrame, text: str, lang: str) -> DataFrame:
    """(lang, gram, n) over all rows with a text and a language."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in slices(batches, "text", PIECE):
            value, at = grams(data, offsets)
            names, code = np.unique(np.asarray(batch.column(1).to_pylist(), dtype=object), return_inverse=True)
            per = np.repeat(code, np.diff(at))
            found, n = np.unique(per.astype(np.uint64) << np.uint64(32) | value.astype(np.uint64), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(names[(found >> np.uint64(32)).astype(np.int64)], pa.string()), pa.array((found & np.uint64(0xFFFFFFFF)).astype(np.int64)), pa.array(n)], names=["lang", "gram", "n"])

    source = docs.where(F.col(text).isNotNull() & F.col(lang).isNotNull()).select(F.col(text).alias("text"), F.col(lang).alias("lang"))
    return source.mapInArrow(run, "lang string, gram bigint, n bigint").groupBy("lang", "gram").agg(F.sum("n").alias("n"))


def learn(docs: DataFrame, text: str = "text", lang: str = "lang") -> Model:
    """Fit the filter on every row of docs."""
    counts = store(gram_counts(docs, text, lang), "grams")
    totals = {r["lang"]: r["n"] for r in counts.groupBy("lang").agg(F.sum("n").alias("n")).collect()}
    languages = sorted(totals)
    if not languages:
        return Model([], np.zeros((1, SLOTS), np.uint64))
    rows = [(k, float(totals[k]), i // LANGUAGES, 1 << i % LANGUAGES) for i, k in enumerate(languages)]
    known = docs.sparkSession.createDataFrame(rows, "lang string, total double, word int, bit bigint")
    own = F.struct((F.col("n") / F.col("total")).alias("rate"), F.greatest(F.lit(float(LEAST)), F.col("total") * LEAST_RATE).alias("least"), "n", "word", "bit")
    per = counts.join(F.broadcast(known), "lang").select("gram", own.alias("own")).groupBy("gram").agg(F.collect_list("own").alias("own"), F.max("own.rate").alias("most"))
    inside = F.filter("own", lambda x: (x["rate"] >= SHARE * F.col("most")) & (x["n"] >= x["least"]))
    members = store(per.select("gram", F.explode(inside).alias("own")).select("gram", "own.word", "own.bit"), "members")
    largest = members.groupBy("word", "bit").count().agg(F.max("count")).first()[0] or 0
    size = slots_for(largest)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s in slots(batch.column(0).to_numpy().astype(np.uint32), size):
                yield pa.RecordBatch.from_arrays([pa.array(s), batch.column(1), batch.column(2)], names=["slot", "word", "mask"])

    masks = np.zeros((-(-len(languages) // LANGUAGES), size), np.uint64)
    of = members.groupBy("gram", "word").agg(F.bit_or("bit").alias("mask"))
    filled = store(of.mapInArrow(place, "slot bigint, word int, mask bigint").groupBy("slot", "word").agg(F.bit_or("mask").alias("mask")), "slots")
    for word in range(len(masks)):  # READ rows at a time, however many n-grams and languages there are
        for low in range(0, size, READ):
            for r in filled.where((F.col("word") == word) & F.col("slot").between(low, low + READ - 1)).select("slot", "mask").toArrow().to_batches():
                masks[word, r.column(0).to_numpy()] = r.column(1).to_numpy().view(np.uint64)
    return Model(languages, masks)


def predict(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """docs with lang_pred and score; every other column stays."""
    names = [c for c in docs.columns if c not in ("lang_pred", "score")]
    out = docs.select(*names)
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in out.schema)
    step = max(1, SHARD_BYTES // model.masks[0].nbytes)
    rates, words = model.false_rates, range(0, len(model.masks), step)

    def shard(low: int):
        last = low + step >= len(model.masks)
        span = slice(low * LANGUAGES, (low + step) * LANGUAGES)
        held = docs.sparkSession.sparkContext.broadcast((model.languages[span], model.masks[low : low + step], rates[span]))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            import regex

            letter = regex.compile(r"\p{L}").search
            languages, masks, wrong = held.value
            ascii_letter = np.zeros(256, bool)
            ascii_letter[[*range(65, 91), *range(97, 123)]] = True
            for batch, data, offsets in slices(batches, text, PIECE):
                n = batch.num_rows
                value, ends = grams(data, offsets)
                count = np.diff(ends)
                first = languages[0] if languages else NONE
                best, score = np.full(n, -1), np.zeros(n)
                if low:
                    score = batch.column(len(names) + 1).to_numpy().copy()
                if len(value) and languages:
                    a, b, c = slots(value, masks.shape[1])
                    for i in range(len(languages)):
                        if i % LANGUAGES == 0:
                            row = masks[i // LANGUAGES]
                            mask = row[a] & row[b] & row[c]
                        sums = np.concatenate([[0], np.cumsum((mask >> np.uint64(i % LANGUAGES)) & np.uint64(1), dtype=np.int64)])
                        hits = sums[ends[1:]] - sums[ends[:-1]]
                        share = (hits / np.maximum(count, 1) - wrong[i]) / max(1 - wrong[i], 1e-9)
                        better = share > score + 1e-12
                        best, score = np.where(better, i, best), np.where(better, np.clip(share, 0, 1), score)
                before = batch.column(len(names)).to_pylist() if low else [first] * n
                pred = [languages[j] if j >= 0 else k for j, k in zip(best.tolist(), before, strict=True)]
                if last:
                    sums = np.concatenate([[0], np.cumsum(ascii_letter[data], dtype=np.int64)])
                    has = sums[offsets[1:]] > sums[offsets[:-1]]
                    for i in np.flatnonzero(~has):
                        raw = data[offsets[i] : offsets[i + 1]]
                        has[i] = bool((raw >= 128).any() and letter(raw.tobytes().decode("utf-8", "replace")))
                    pred = [p if k else NONE for p, k in zip(pred, has.tolist(), strict=True)]
                    score = np.where(has, score, 0.0)
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], pa.array(pred, pa.string()), pa.array(score)], names=[*names, "lang_pred", "score"])

        return run

    for low in words:
        out = out.mapInArrow(shard(low), f"{kinds}, lang_pred string, score double")
        if low != words[-1]:
            out = store(out, "judged")
    return out


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = learn(docs.where(fold_of("doc_id") != 0).select("text", "lang"))
    return predict(docs.select("doc_id", "text"), model).select("doc_id", (fold_of("doc_id") == 0).alias("held_out"), "lang_pred", "score")


