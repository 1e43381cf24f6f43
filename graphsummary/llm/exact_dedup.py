"""Exact duplicates by deterministic block naming.

Texts are cut into fixed-size blocks of bytes. The blocks are sorted and equal ones get one number; then adjacent pairs of
numbers are sorted and numbered, again and again, until each text has one number. Two texts of the same byte length have
the same number exactly if they are the same: names come from comparing whole blocks, so no hash can collide. The order is
by a hash of the block first and by the whole block then, so that blocks with a common beginning spread over all ranges.
Every row gets its number so; SHA-256 is only a column of the result.

A null text counts as empty. Repeated rows each get a row and count in group_size. The row with the largest doc_id
stays (kept is true on every repeat of it); a null doc_id stays only where a group has no other. An empty table gives
no rows. A very long text is many blocks, each a row of its own; only the row that holds the text has it whole. Other
columns are left out, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphsummary.llm.common import discard, documents, small, store

BLOCK_BYTES = 2048
#: Blocks of one hash that a task may number, and the tasks that share more of them.
HOT, SALTS = 1000, 64


def name_sorted(values: DataFrame, columns: list[str]) -> DataFrame:
    """Number the distinct rows in sorted order: equal rows share a number, others differ."""
    spread = values.select(*columns).distinct().withColumn("spread", F.xxhash64(*columns))
    ranked = spread.repartitionByRange("spread").sortWithinPartitions("spread", *columns).withColumn("name", F.monotonically_increasing_id())
    return store(ranked.drop("spread"), "names")


def _first_names(texts: DataFrame, text: str, block: int, keep: tuple[str, ...]) -> DataFrame:
    """(row, n_bytes, at, name, *keep) for every block, stored; keep stands with a text's first block only.

    All blocks are shuffled once, by their hash, and numbered in the order of hash and whole block. Hashes of more than HOT
    blocks are dealt to SALTS tasks; the numbers that these give to one block are made one afterwards.
    """
    count = F.greatest(F.lit(1), F.ceil(F.col("n_bytes") / block)).cast("int")
    cut = texts.select("row", "n_bytes", text, *keep, F.explode(F.sequence(F.lit(0), count - 1)).alias("at"))
    own = [F.when(F.col("at") == 0, F.col(c)).alias(c) for c in keep]
    cut = cut.select("row", "n_bytes", F.col("at").cast("bigint").alias("at"), *own, F.substring(F.col(text), F.col("at") * block + 1, F.lit(block)).alias("block")).withColumn("spread", F.xxhash64("block"))
    hot = small(store(cut.groupBy("spread").agg(F.count("*").alias("n")).where(F.col("n") > HOT).select("spread", F.lit(True).alias("hot")), "hot"))
    dealt = cut.join(hot, "spread", "left").withColumn("salt", F.when(F.col("hot"), F.pmod(F.xxhash64("row"), F.lit(SALTS))).otherwise(F.lit(0)))
    dealt = dealt.repartition("spread", "salt").sortWithinPartitions("spread", "salt", "block").withColumn("id", F.monotonically_increasing_id())
    named = dealt.withColumn("name", F.min("id").over(Window.partitionBy("spread", "salt", "block")))
    shown = F.when(F.col("hot") & (F.col("id") == F.col("name")), F.col("block")).alias("shown")  # SALTS at most for a block
    named = store(named.select("row", "n_bytes", "at", "name", *keep, shown), "named")
    same = named.where("shown is not null").groupBy("shown").agg(F.min("name").alias("first"), F.collect_list("name").alias("names"))
    same = small(store(same.select(F.explode("names").alias("name"), "first").where("name <> first"), "same"))
    return named.join(same, "name", "left").select("row", "n_bytes", "at", F.coalesce("first", "name").alias("name"), *keep)


def block_names(texts: DataFrame, text: str, block: int = BLOCK_BYTES, keep: tuple[str, ...] = ()) -> DataFrame:
    """(row, n_bytes, name, *keep) for each text; texts holds its unique `row`, its byte length `n_bytes`, the binary text and
    what is to be kept.

    Texts of one length take part in the same rounds, so that names are comparable between texts of one length.
    """
    first, covered, done = _first_names(texts, text, block, keep), block, []
    now = first.drop(*keep)
    longest = first.agg(F.max("n_bytes")).first()[0] or 0
    while covered < longest:
        done.append(now.where(F.col("n_bytes") <= covered).drop("at"))
        name_at = lambda odd: F.min(F.when(F.col("at") % 2 == odd, F.col("name")))
        pairs = now.where(F.col("n_bytes") > covered).groupBy("row", "n_bytes", F.floor(F.col("at") / 2).alias("at")).agg(name_at(0).alias("left"), F.coalesce(name_at(1), F.lit(-1)).alias("right"))
        pairs = store(pairs, "pairs")
        names = name_sorted(pairs, ["left", "right"])
        now, covered = store(pairs.join(names, ["left", "right"]).select("row", "n_bytes", "at", "name"), "named"), covered * 2
        for old in (pairs, names):
            discard(old)
    out = now.drop("at")
    for part in done:
        out = out.union(part)
    return out.join(first.where("at = 0").select("row", *keep), "row") if keep else out


def exact_groups(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", block: int = BLOCK_BYTES) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256) for every row of docs."""
    raw = docs.select(F.col(doc_id).alias("doc_id"), F.encode(F.coalesce(F.col(text), F.lit("")), "utf-8").alias("raw"))
    marked = raw.withColumns({"n_bytes": F.octet_length("raw").cast("bigint"), "sha": F.unhex(F.sha2("raw", 256))})
    named = store(block_names(marked.withColumn("row", F.monotonically_increasing_id()), "raw", block, ("doc_id", "sha")), "identity")
    groups = named.groupBy("n_bytes", "name").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    grouped = named.join(groups, ["n_bytes", "name"])
    return grouped.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("sha")).alias("text_sha256"))


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(documents(spark, sf_dir))


OP4_SQL = """
with t as (select doc_id, coalesce(text, '') as text from documents)
select doc_id, max(doc_id) over same as keep_id, count(*) over same as group_size, doc_id = max(doc_id) over same as kept, sha256(text) as text_sha256
from t window same as (partition by text)
"""
