"""Secrets in texts: an Aho-Corasick pass finds keywords, anchored expressions look only where one stands, and tokens
that carry a checksum are verified.

Kinds: `assign` (a password-like name with a value), `access` (access key ids), `hex` (long runs of hex digits; they
have no keyword, so one run pattern goes over the text), and `hosted` and `package` (tokens whose last six base-62
digits are the CRC-32 of what stands before). Spans are in code points, the end excluded.

Null counts as the empty text, which has no spans. Repeated rows are scanned alike, an empty table gives no rows,
further columns are left out. Whole texts are scanned.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm.common import documents

# fixed values: the kinds' patterns and lengths
KINDS = ("assign", "access", "hex", "hosted", "package")
BASE_KINDS = ("assign", "access", "hex")
NAMES = ("password", "passwd", "secret", "token", "api_key", "apikey")
ASSIGN = r"""(?:(?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]{16,}"
HOSTED = r"gh[pousr]_[0-9A-Za-z]{36}(?![0-9A-Za-z])"
PACKAGE = r"npm_[0-9A-Za-z]{36}(?![0-9A-Za-z])"
HOSTED_NAMES = ("ghp_", "gho_", "ghu_", "ghs_", "ghr_")
LEAST_VALUE, LEAST_ACCESS = 12, 18
DIGITS = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"


def checksum(body: str) -> str:
    """CRC-32 of the text in six base-62 digits."""
    n, out = zlib.crc32(body.encode()), ""
    for _ in range(6):
        n, d = divmod(n, 62)
        out = DIGITS[d] + out
    return out


class Scanner:
    def __init__(self):
        import ahocorasick

        self.words = ahocorasick.Automaton()
        for kind, names in (("assign", NAMES), ("access", ("akia",)), ("hosted", HOSTED_NAMES), ("package", ("npm_",))):
            for name in names:
                self.words.add_word(name, (kind, len(name)))
        self.words.make_automaton()
        self.at = {k: re.compile(p, re.ASCII).match for k, p in (("assign", ASSIGN), ("access", ACCESS), ("hosted", HOSTED), ("package", PACKAGE))}
        self.hex = re.compile(HEX).finditer

    def __call__(self, text: str) -> list[tuple[int, int, str]]:
        """(start, end, kind) of every secret, by start and then by the order of KINDS."""
        found = [(m.start(), m.end(), "hex") for m in self.hex(text)]
        lower = text.encode("utf-8", "surrogatepass").lower().decode("utf-8", "surrogatepass")  # A-Z only: positions stay
        past = dict.fromkeys(KINDS, 0)
        hits = sorted((end + 1 - n, kind) for end, (kind, n) in self.words.iter(lower))
        for start, kind in hits:
            if start < past[kind] or not (m := self.at[kind](text, start)):
                continue
            past[kind] = m.end()
            if kind == "assign":
                good = len(m[1]) >= LEAST_VALUE
            elif kind == "access":
                good = m.end() - start >= LEAST_ACCESS
            else:
                body = text[start + 4 : m.end()]
                good = checksum(body[:-6]) == body[-6:]
            if good:
                found.append((start, m.end(), kind))
        return sorted(found, key=lambda x: (x[0], KINDS.index(x[2])))


def joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, end, kind in spans)


def find_secrets(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, spans array<struct<kind, start, end>>) of every text."""
    source = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    kind = source.schema["doc_id"].dataType.simpleString()
    span = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scan = Scanner()
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                rows = [[{"kind": k, "start": a, "end": b} for a, b, k in scan(t.as_py())] for t in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(rows, span)], names=["doc_id", "spans"])

    return source.mapInArrow(run, f"doc_id {kind}, spans array<struct<kind: string, start: int, end: int>>")


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_secrets(documents(spark, sf_dir))
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE_KINDS))
    text = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    count = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("bigint").alias(f"n_{k}")
    return found.select("doc_id", *map(count, BASE_KINDS), F.sha2(text(base).cast("binary"), 256).alias("base_sha256"), text(F.col("spans")).alias("spans"))


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """The base kinds by plain scans of the whole text, for tests."""
    out = [(m.start(), m.end(), "assign") for m in re.finditer(ASSIGN, text, re.ASCII) if len(m[1]) >= LEAST_VALUE]
    out += [(m.start(), m.end(), "access") for m in re.finditer(ACCESS, text) if len(m[0]) >= LEAST_ACCESS]
    out += [(m.start(), m.end(), "hex") for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 16]
    return sorted(out, key=lambda x: (x[0], KINDS.index(x[2])))


def base_digest(text: str) -> str:
    return hashlib.sha256(joined(base_spans(text)).encode()).hexdigest()
