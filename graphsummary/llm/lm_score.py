"""Language-model scores by deleted interpolation of word bigrams, unigrams and the uniform distribution.

Maximum-likelihood estimates are mixed with weights that depend on how often the context was seen (its bucket). A tenth
of the training documents is held out; expectation-maximisation finds the weights under which counts of the rest explain
the held-out tokens. The scores then use the counts of all training documents.

Counting moves arrays, not rows: every worker turns a piece of the corpus (a chunk) into its distinct n-gram hashes with
their counts and sends each range of hashes as one compressed array; a range is summed in one place, and the totals go
back in the order in which the chunk sent its hashes. The chunk's text, compressed, meets its totals and is scored.
Chunks are numbered by partition and order, so the input has to be cut alike when it is read again, as a stored table is;
a difference is noticed, by a digest of each chunk's n-grams, and raises.

A null text is the empty text: one token, the end. Without training documents every estimate is uniform. Repeated rows
are scored (and counted) as separate documents. An empty table gives no rows. Other columns are left out, whatever their
names. A text is never cut: one longer than a chunk is a chunk of its own and takes about 30 times its bytes in a worker.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm.common import documents, fold_of, mix, slices, store, words

#: Text in a chunk; and about the text whose n-grams meet in one range of hashes, at RANGE_AT bytes of input. A range grows
#: with the square root of the input up to RANGE_MOST, what a worker can hold, so that the arrays exchanged grow as the input.
CHUNK_BYTES, RANGE_BYTES, RANGE_MOST, RANGE_AT = 8 << 20, 4 << 20, 32 << 20, 512 << 20
#: Roles: scored only, counted, counted and held out for the weights.
OTHER, COUNTED, HELD = 0, 1, 2
BUCKETS, LEVELS, STEPS = 42, 256, 60
_END, _START = np.uint64(0x8A5CD789635D2DFF), np.uint64(0x121FD2155C472F96)
_PAIR = np.uint64(0xD6E8FEB86659FD93)
_GRAMS = "chunk string, part int, held boolean, rows int, hashes binary, counts binary"
_TOTALS = "chunk string, part int, rows int, digest bigint, totals binary, types bigint, tokens bigint, rest_tokens bigint"


def packed(values: np.ndarray) -> bytes:
    """Byte planes of an array, compressed."""
    return pa.compress(np.ascontiguousarray(values.view(np.uint8).reshape(len(values), -1).T).tobytes(), codec="zstd", asbytes=True)


def unpacked(raw: bytes, rows: int, kind: type) -> np.ndarray:
    width = np.dtype(kind).itemsize
    planes = np.frombuffer(pa.decompress(raw, rows * width, codec="zstd", asbytes=True), np.uint8)
    return np.ascontiguousarray(planes.reshape(width, rows).T).view(kind).ravel()


def tokens(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Token hashes (odd), the contexts before them, and the texts' offsets; an end token closes every text."""
    w, at = words(data, offsets)
    one = np.uint64(1)
    t = np.insert(w | one, at[1:], _END)
    ends = at + np.arange(len(at))
    before = np.empty_like(t)
    before[1:] = t[:-1]
    before[ends[:-1]] = _START
    return t, before, ends


def ngrams(t: np.ndarray, before: np.ndarray, counted: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct n-gram hashes, their counts over counted tokens, and where tokens, pairs and contexts stand.

    Unigrams are odd; pairs and the start of a text are even.
    """
    pair = mix(before * _PAIR + t) & ~np.uint64(1)
    starts = (before == _START) & counted
    every = np.concatenate([t, pair, [_START]])
    found, at = np.unique(every, return_inverse=True)
    n = len(t)
    weight = np.concatenate([counted, counted, [0]]).astype(np.float64)
    count = np.bincount(at, weight, len(found)).astype(np.uint32)
    count[at[-1]] = starts.sum()
    context = np.empty(n, np.int64)
    context[1:] = at[: n - 1]
    context[before == _START] = at[-1]
    return found, count, at[:n], at[n : 2 * n], context


def chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[str, bool, pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Pieces of (doc_id, text, role); held-out documents stand in chunks of their own."""
    part, k = TaskContext.get().partitionId(), 0
    for batch in batches:
        role = batch.column(2).to_numpy(zero_copy_only=False)
        for held in (False, True):
            own = batch.take(pa.array(np.flatnonzero((role == HELD) == held)))
            for piece, data, offsets in slices(iter([own]), "text", CHUNK_BYTES):
                yield f"{part}-{k}", held, piece, data, offsets
                k += 1


def _send(ranges: int):
    shift = np.uint64(64 - ranges.bit_length() + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for chunk, held, piece, data, offsets in chunks(batches):
            t, before, ends = tokens(data, offsets)
            counted = np.repeat(piece.column(2).to_numpy(zero_copy_only=False) != OTHER, np.diff(ends))
            found, count, *_ = ngrams(t, before, counted)
            part = (found >> shift).astype(np.int64) if ranges > 1 else np.zeros(len(found), np.int64)
            cut = np.flatnonzero(np.diff(part, prepend=-1))
            rows = []
            for a, b in zip(cut, [*cut[1:], len(found)], strict=True):
                rows.append((int(part[a]), b - a, packed(np.diff(found[a:b], prepend=np.uint64(0))), packed(count[a:b])))
            p, n, h, c = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array([chunk] * len(p)), pa.array(p, pa.int32()), pa.array([held] * len(p)), pa.array(n, pa.int32()), pa.array(h, pa.binary()), pa.array(c, pa.binary())], names=["chunk", "part", "held", "rows", "hashes", "counts"])

    return run


def digest(hashes: np.ndarray) -> int:
    """A sum that differs for other hashes; those of parts add up to that of the whole, modulo 2 ** 64."""
    return int(mix(hashes).view(np.int64).sum(dtype=np.int64))


def _sum_range(table: pa.Table) -> pa.Table:
    rows = table.column("rows").to_pylist()
    own = [np.cumsum(unpacked(h, n, np.uint64), dtype=np.uint64) for h, n in zip(table.column("hashes").to_pylist(), rows, strict=True)]
    hashes, digests = np.concatenate(own), [digest(x) for x in own]
    counts = np.concatenate([unpacked(c, n, np.uint32) for c, n in zip(table.column("counts").to_pylist(), rows, strict=True)]).astype(np.int64)
    held = np.repeat(np.array(table.column("held").to_pylist(), bool), rows)
    found, at = np.unique(hashes, return_inverse=True)
    every = np.bincount(at, counts, len(found)).astype(np.int64)
    rest = every - np.bincount(at, counts * held, len(found)).astype(np.int64)
    single = (found & np.uint64(1)) == 1
    totals = np.stack([every, rest], 1)[at].astype(np.uint64)
    ends = np.cumsum(rows)
    back = [packed(np.ascontiguousarray(totals[b - n : b]).ravel()) for b, n in zip(ends, rows, strict=True)]
    k, part = len(rows), table.column("part")[0].as_py()
    zero = [0] * k
    return pa.table({
        "chunk": pa.array([*table.column("chunk").to_pylist(), None], pa.string()), "part": pa.array([part] * (k + 1), pa.int32()), "rows": pa.array([*rows, 0], pa.int32()), "digest": pa.array([*digests, 0], pa.int64()), "totals": pa.array([*back, None], pa.binary()),
        "types": pa.array([*zero, int((single & (every > 0)).sum())], pa.int64()), "tokens": pa.array([*zero, int(every[single].sum())], pa.int64()), "rest_tokens": pa.array([*zero, int(rest[single].sum())], pa.int64()),
    })


def _texts(held_only: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for chunk, held, piece, data, offsets in chunks(batches):
            if held or not held_only:
                raw = pa.compress(data.tobytes(), codec="zstd", asbytes=True)
                ids = pa.ListArray.from_arrays(pa.array([0, piece.num_rows], pa.int32()), piece.column(0))
                role = pa.ListArray.from_arrays(pa.array([0, piece.num_rows], pa.int32()), piece.column(2))
                at = pa.ListArray.from_arrays(pa.array([0, len(offsets)], pa.int32()), pa.array(offsets, pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array([chunk]), ids, role, at, pa.array([raw], pa.binary())], names=["chunk", "ids", "roles", "offsets", "raw"])

    return run


def _counted(texts: pa.Table, totals: pa.Table):
    """A chunk's text again with the counts of its n-grams: all, and without the held-out documents."""
    offsets = texts.column("offsets").combine_chunks().values.to_numpy()
    data = np.frombuffer(pa.decompress(texts.column("raw")[0].as_py(), int(offsets[-1]), codec="zstd", asbytes=True), np.uint8)
    t, before, ends = tokens(data, offsets)
    found, _, own, pair, context = ngrams(t, before, np.zeros(len(t), bool))
    parts = sorted(zip(totals.column("part").to_pylist(), totals.column("rows").to_pylist(), totals.column("totals").to_pylist(), strict=True))
    sent = np.array(totals.column("digest").to_pylist(), np.int64).sum(dtype=np.int64)
    if sum(n for _, n, _ in parts) != len(found) or sent != digest(found):
        raise ValueError("the documents were cut differently when they were read again; store them first")
    counts = np.concatenate([unpacked(raw, 2 * n, np.uint64).reshape(-1, 2) for _, n, raw in parts]).astype(np.float64)
    return ends, counts[own], counts[pair], counts[context]


def _bucket(context: np.ndarray) -> np.ndarray:
    """0 for an unseen context, then one for each doubling of its count."""
    return np.minimum(np.where(context > 0, np.floor(np.log2(np.maximum(context, 1))) + 1, 0), BUCKETS - 1).astype(np.int64)


def _level(p: np.ndarray) -> np.ndarray:
    """A probability in quarters of a bit, 0 for none."""
    return np.where(p > 0, np.minimum(np.round(-4 * np.log2(np.where(p > 0, p, 1))) + 1, LEVELS - 1), 0).astype(np.int64)


def _held_cells(rest_tokens: int):
    def run(key, texts: pa.Table, totals: pa.Table) -> pa.Table:
        if not texts.num_rows:
            return pa.table({"cell": pa.array([], pa.int64()), "n": pa.array([], pa.int64())})
        _, own, pair, context = _counted(texts, totals)
        c = context[:, 1]
        p2 = np.divide(pair[:, 1], c, out=np.zeros(len(c)), where=c > 0)
        p1 = own[:, 1] / max(rest_tokens, 1)
        cell, n = np.unique((_bucket(c) * LEVELS + _level(p2)) * LEVELS + _level(p1), return_counts=True)
        return pa.table({"cell": pa.array(cell), "n": pa.array(n)})

    return run


def fit_weights(cell: np.ndarray, n: np.ndarray, types: int, steps: int = STEPS) -> np.ndarray:
    """(BUCKETS, 3) weights of pair, word and uniform estimates by EM; a bucket without tokens gets the overall ones."""
    bucket, l2, l1 = cell // (LEVELS * LEVELS), cell // LEVELS % LEVELS, cell % LEVELS
    p = np.stack([np.where(l2 > 0, 2.0 ** (-(l2 - 1) / 4), 0), np.where(l1 > 0, 2.0 ** (-(l1 - 1) / 4), 0), np.full(len(cell), 1 / (types + 1))], 1)

    def run(p: np.ndarray, n: np.ndarray) -> np.ndarray:
        w = np.full(3, 1 / 3)
        for _ in range(steps):
            part = p * w
            w = (part / part.sum(1, keepdims=True) * n[:, None]).sum(0)
            w /= w.sum()
        w = np.maximum(w, 1e-6)
        return w / w.sum()

    overall = run(p, n) if len(n) else np.array([0.0, 0.0, 1.0]) if types == 0 else np.full(3, 1 / 3)
    out = np.tile(overall, (BUCKETS, 1))
    for b in np.unique(bucket):
        out[b] = run(p[bucket == b], n[bucket == b])
    out[0, 0] = 0  # an unseen context has no pair estimate
    return out / out.sum(1, keepdims=True)


def _scored(weights: np.ndarray, types: int, total: int, kind: pa.DataType):
    def run(key, texts: pa.Table, totals: pa.Table) -> pa.Table:
        names = ["doc_id", "role", "n_tokens", "n_known", "base_score", "score"]
        if not texts.num_rows:
            return pa.table([pa.array([], x) for x in (kind, pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.float64())], names=names)
        ends, own, pair, context = _counted(texts, totals)
        c, ctx = own[:, 0], context[:, 0]
        base = np.log10((c + 0.5) / (total + 0.5 * (types + 1)))
        w = weights[_bucket(ctx)]
        p2 = np.divide(pair[:, 0], ctx, out=np.zeros(len(ctx)), where=ctx > 0)
        model = np.log10(w[:, 0] * p2 + w[:, 1] * c / max(total, 1) + w[:, 2] / (types + 1))
        add = lambda x: np.add.reduceat(x, ends[:-1])  # noqa: E731  no text is without a token
        ids, roles = (texts.column(x).combine_chunks().values for x in ("ids", "roles"))
        return pa.table([ids, roles, pa.array(np.diff(ends)), pa.array(add((c > 0).astype(np.int64))), pa.array(add(base)), pa.array(add(model))], names=names)

    return run


def score(docs: DataFrame, role: Column, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, role, n_tokens, n_known, train_tokens, base_score, score) of every text; role as named above."""
    source = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"), role.cast("int").alias("role"))
    field = source.schema["doc_id"].dataType
    kind = field.simpleString()
    size = source.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    per_range = min(max(RANGE_BYTES * (size / RANGE_AT) ** 0.5, RANGE_BYTES), RANGE_MOST)
    ranges = 1 << max(0, int(np.ceil(np.log2(max(1, size / per_range)))))
    totals = store(source.mapInArrow(_send(ranges), _GRAMS).groupBy("part").applyInArrow(_sum_range, _TOTALS), "totals")
    sums = totals.agg(F.sum("types"), F.sum("tokens"), F.sum("rest_tokens")).first()
    types, total, rest = (int(x or 0) for x in sums)
    back = totals.where("chunk is not null").select("chunk", "part", "rows", "digest", "totals").groupBy("chunk")
    shape = f"chunk string, ids array<{kind}>, roles array<int>, offsets array<bigint>, raw binary"
    held = source.mapInArrow(_texts(True), shape).groupBy("chunk").cogroup(back).applyInArrow(_held_cells(rest), "cell bigint, n bigint")
    cells = held.groupBy("cell").agg(F.sum("n").alias("n")).toPandas()  # BUCKETS * LEVELS * LEVELS rows at most
    weights = fit_weights(cells["cell"].to_numpy(np.int64), cells["n"].to_numpy(np.int64), types)
    from pyspark.sql.pandas.types import to_arrow_type

    made = source.mapInArrow(_texts(False), shape).groupBy("chunk").cogroup(back).applyInArrow(
        _scored(weights, types, total, to_arrow_type(field)), f"doc_id {kind}, role int, n_tokens bigint, n_known bigint, base_score double, score double")
    return made.withColumn("train_tokens", F.lit(total).cast("bigint"))


def op7_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    tenth = F.coalesce(F.floor(F.crc32(F.col("doc_id").cast("string").cast("binary")) / 5) % 10, F.lit(1))
    role = F.when(fold_of("doc_id") == 1, OTHER).when(tenth == 0, HELD).otherwise(COUNTED)
    made = score(docs, role)
    return made.select("doc_id", (F.col("role") == OTHER).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")
