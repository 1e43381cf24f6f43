"""Token counts of a byte-level BPE vocabulary by rank-synchronous array merging.

Pre-tokens are held as one ragged array of symbols. Each step looks up the rank of every adjacent pair, finds each
sequence's lowest rank, merges all places of that pair in all sequences at once (overlapping places from the left) and
retires sequences without a known pair. The symbols that survive are counted. A merged symbol's own pairs always have
higher ranks than the merge that made it, so merging all places of a pair together gives the same result as one by one.
A sequence of more than LONG symbols goes through the same ranks with its places held by rank, so that a step touches the
neighbours of changed places only; its time is near linear in its length.

Null and empty texts have no tokens. Whole texts are counted; a special string inside a text is one token, as by the
library's default. Repeated rows are counted alike, an empty table gives no rows, further columns are left out, whatever
their names.
"""

from __future__ import annotations

import heapq
import json
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm.common import documents

#: The vocabulary's pre-token pattern (fixed value), with the white space property spelt out.
PRE_TOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
#: Pre-tokens that a task remembers before it starts afresh.
REMEMBER = 400_000
#: Symbols from which a sequence's places are held by rank.
LONG = 2_000
_NONE = np.int64(1 << 60)


def byte_symbols() -> dict[int, str]:
    """The printable character that stands for each byte: printable Latin-1 for itself, the others from U+0100 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    other = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(other)}


@dataclass
class Ranks:
    """A merge table as arrays: pairs (left << 32 | right) in order, with the rank and the symbol they give."""

    start: np.ndarray
    pairs: np.ndarray
    rank: np.ndarray
    made: np.ndarray
    special: list[str]

    @classmethod
    def read(cls, path: str) -> Ranks:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        if (spec.get("pre_tokenizer") or {}).get("type") != "ByteLevel" or spec.get("normalizer"):
            raise ValueError("only byte-level vocabularies without a normalizer, which have the pattern above, are known")
        vocab = spec["model"]["vocab"]
        merges = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        symbols = byte_symbols()
        pairs = np.array([vocab[a] << 32 | vocab[b] for a, b in merges], np.int64)
        made = np.array([vocab[a + b] for a, b in merges], np.int64)
        order = np.argsort(pairs)
        start = np.array([vocab[symbols[b]] for b in range(256)], np.int64)
        return cls(start, pairs[order], order.astype(np.int64), made[order], [t["content"] for t in spec.get("added_tokens", [])])

    def counts(self, pieces: list[bytes]) -> np.ndarray:
        """Symbols left of each non-empty piece."""
        out = np.zeros(len(pieces), np.int64)
        owner = []
        for i, piece in enumerate(pieces):
            if len(piece) > LONG:
                out[i] = self.long_count(piece)
            else:
                owner.append(i)
        owner = np.array(owner, np.int64)
        lens = np.fromiter((len(pieces[i]) for i in owner), np.int64, len(owner))
        symbol = self.start[np.frombuffer(b"".join(pieces[i] for i in owner), np.uint8)]
        while len(owner):
            first = np.cumsum(lens) - lens
            key = np.full(len(symbol), -1, np.int64)
            key[:-1] = symbol[:-1] << 32 | symbol[1:]
            key[first + lens - 1] = -1  # no pair begins at a sequence's end
            at = np.minimum(np.searchsorted(self.pairs, key), len(self.pairs) - 1)
            rank = np.where(self.pairs[at] == key, self.rank[at], _NONE)
            lowest = np.minimum.reduceat(rank, first)
            done = lowest == _NONE
            out[owner[done]] = lens[done]
            merge = (rank == np.repeat(lowest, lens)) & (rank != _NONE)
            place = np.arange(len(symbol))
            begins = merge.copy()
            begins[1:] &= ~merge[:-1]
            merge &= (place - np.maximum.accumulate(np.where(begins, place, 0))) % 2 == 0
            symbol = np.where(merge, self.made[at], symbol)
            keep = np.ones(len(symbol), bool)
            keep[1:] = ~merge[:-1]
            lens = lens - np.add.reduceat(merge.astype(np.int64), first)
            keep &= np.repeat(~done, np.add.reduceat(np.ones(len(symbol), np.int64), first))
            symbol, lens, owner = symbol[keep], lens[~done], owner[~done]
        return out

    def long_count(self, piece: bytes) -> int:
        """Symbols left of one long piece: the lowest rank's places at once, then new pairs beside them."""
        known = dict(zip(self.pairs.tolist(), zip(self.rank.tolist(), self.made.tolist(), strict=True), strict=True))
        symbol = self.start[np.frombuffer(piece, np.uint8)].tolist()
        n = left = len(symbol)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        places: dict[int, list[int]] = {}
        heap: list[int] = []

        def add(i: int) -> None:
            if i >= 0 and (j := after[i]) < n and (to := known.get(symbol[i] << 32 | symbol[j])):
                if to[0] not in places:
                    places[to[0]] = []
                    heapq.heappush(heap, to[0])
                places[to[0]].append(i)

        for i in range(n - 1):
            add(i)
        while heap:
            rank = heapq.heappop(heap)
            merged = []
            for i in sorted(places.pop(rank)):  # from the left; a place whose pair has gone is passed over
                if symbol[i] < 0 or (j := after[i]) >= n or (to := known.get(symbol[i] << 32 | symbol[j])) is None or to[0] != rank:
                    continue
                symbol[i], symbol[j], after[i] = to[1], -1, after[j]
                if after[i] < n:
                    before[after[i]] = i
                merged.append(i)
            left -= len(merged)
            for i in merged:
                add(before[i])
                add(i)
        return left


class Counter:
    """Counts the tokens of texts, remembering pre-tokens seen before."""

    def __init__(self, ranks: Ranks):
        import regex

        self.ranks, self.known = ranks, {}
        self.pre_tokens = regex.compile(PRE_TOKEN).findall
        self.special = regex.compile("|".join(map(regex.escape, ranks.special))) if ranks.special else None

    def __call__(self, texts: list[str]) -> list[int]:
        if len(self.known) > REMEMBER:
            self.known = {}
        parts, extra = [], []
        for t in texts:
            whole = self.special.split(t) if self.special else [t]
            extra.append(len(whole) - 1)
            parts.append([x for p in whole for x in self.pre_tokens(p)])
        known = self.known
        new = list({x for p in parts for x in p if x not in known})
        if new:
            known.update(zip(new, self.ranks.counts([x.encode("utf-8", "surrogatepass") for x in new]).tolist(), strict=True))
        return [n + sum(map(known.__getitem__, p)) for n, p in zip(extra, parts, strict=True)]


def count_tokens(docs: DataFrame, path: str, doc_id: str = "doc_id", text: str = "text", rows: int = 200) -> DataFrame:
    """(doc_id, n_bytes, n_tokens) of every text. path: the vocabulary file, read on the driver only."""
    ranks = Ranks.read(path)
    held = docs.sparkSession.sparkContext.broadcast((ranks.start, ranks.pairs, ranks.rank, ranks.made, ranks.special))
    source = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    source = source.withColumn("n_bytes", F.octet_length("text").cast("bigint"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = Counter(Ranks(*held.value))
        for batch in batches:
            for lo in range(0, batch.num_rows, rows):
                part = batch.slice(lo, rows)
                n = pa.array(count(part.column(1).to_pylist()), pa.int64())
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), n], names=["doc_id", "n_bytes", "n_tokens"])

    kind = source.schema["doc_id"].dataType.simpleString()
    return source.mapInArrow(run, f"doc_id {kind}, n_bytes bigint, n_tokens bigint")


#: Tokens that a document may have in the registered query.
LIMIT = 1024


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    counted = count_tokens(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"))
    return counted.withColumn("over_limit", F.col("n_tokens") > LIMIT)
