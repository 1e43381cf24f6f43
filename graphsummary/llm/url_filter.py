"""URL allow and block lists held in Bloom filter cascades; native DataFrame operations only.

A cascade answers membership exactly for every key that the corpus can ask about: level 1 holds the listed keys,
level 2 the corpus keys that pass level 1 without being listed, level 3 the listed keys that pass level 2, and so on
until a level has no false positive. Judging a row is then a few bit tests, without a join or a shuffle.

Null urls and urls without "://" have empty host and path, fit no rule and are allowed. Repeated rows are judged
alike, an empty table gives no rows, further columns of the table are left out.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm.common import LOWER, UPPER, store

#: Largest level in 64-bit words (8 MB). A longer list is looked up with a hash join instead.
MAX_WORDS = 1 << 20
BITS_PER_KEY, PROBES = 12, 6


@dataclass
class Level:
    bits: DataFrame  # one row, one array<bigint>
    words: int
    seed: int

    def has(self, key: Column) -> Column:
        words = self.bits.scalar()
        hit = F.lit(True)
        for place in _places(key, self.words, self.seed):
            hit &= F.getbit(F.get(words, F.floor(place / 64).cast("int")), (place % 64).cast("int")) == 1
        return hit


def _places(key: Column, words: int, seed: int) -> list[Column]:
    return [F.pmod(F.xxhash64(key, F.lit(seed), F.lit(j)), F.lit(words * 64)) for j in range(PROBES)]


def bloom(keys: DataFrame, count: int, seed: int) -> Level:
    """A filter over the column `key`, as one row with an array of 64-bit words."""
    words = max(1, -(-count * BITS_PER_KEY // 64))
    place = keys.select(F.explode(F.array(*_places(F.col("key"), words, seed))).alias("place"))
    one = F.call_function("shiftleft", F.lit(1).cast("bigint"), (F.col("place") % 64).cast("int"))
    set_bits = place.groupBy(F.floor(F.col("place") / 64).alias("id")).agg(F.bit_or(one).alias("bits"))
    dense = keys.sparkSession.range(words).join(set_bits, "id", "left")
    ordered = F.array_sort(F.collect_list(F.struct("id", F.coalesce("bits", F.lit(0).cast("bigint")).alias("bits"))))
    return Level(store(dense.agg(ordered["bits"].alias("bits")), "bloom"), words, seed)


@dataclass
class Cascade:
    levels: list[Level]

    def member(self, key: Column) -> Column:
        """Exact for listed keys and for every key of the universe that the cascade was built over."""
        found = F.lit(len(self.levels) % 2 == 1)
        for depth in range(len(self.levels), 0, -1):
            found = F.when(self.levels[depth - 1].has(key), found).otherwise(F.lit(depth % 2 == 0))
        return found


def cascade(universe: DataFrame, listed: DataFrame, seed: int = 17) -> Cascade:
    """universe and listed have one column, key. The universe may repeat keys and include listed ones."""
    inside = store(listed.where(F.col("key").isNotNull()).distinct(), "listed")
    count, levels = inside.count(), []
    outside = universe.where(F.col("key").isNotNull())
    first = True
    while count:
        if -(-count * BITS_PER_KEY // 64) > MAX_WORDS:
            raise ValueError(f"{count} keys need more than {MAX_WORDS} words; use judge(..., listed_join=True)")
        levels.append(bloom(inside, count, seed + 101 * len(levels)))
        passed = outside.where(levels[-1].has(F.col("key")))
        if first:  # the whole universe is read once; only what passes is made distinct
            passed, first = passed.distinct().join(inside, "key", "left_anti"), False
        inside, outside = store(passed, "passed"), inside
        count = inside.count()
    return Cascade(levels)


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"://[^/?#]*([^?#]*)", 1), F.lit(""))


def candidates(host: Column, path: Column, lengths: list[int]) -> Column:
    """Every rule that could fit, longest first (of equal length, the longer host first)."""
    labels = F.split(host, r"\.")
    hosts = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    starts = F.filter(F.array(*[F.lit(n) for n in lengths]), lambda n: n <= F.length(path))
    keys = F.flatten(F.transform(hosts, lambda h: F.transform(starts, lambda n: F.struct((-F.length(h) - n).alias("order"), (-F.length(h)).alias("host_order"), F.concat(h, F.substr(path, F.lit(1), n)).alias("key")))))
    return F.transform(F.array_sort(keys), lambda x: x["key"])


def judge(pages: DataFrame, block: list[str], allow: list[str], url: str = "url", listed_join: bool = False) -> DataFrame:
    """Add host, path, rule and verdict to pages; rules are host plus path prefix and fit subdomains too.

    The longest fitting rule decides; a rule on both lists blocks; without a rule the url is allowed. listed_join
    looks candidates up with a join instead of cascades, for lists beyond MAX_WORDS.
    """
    spark: SparkSession = pages.sparkSession
    rules = sorted({*block, *allow})
    lengths = sorted({len(r) - len(r.split("/")[0]) for r in rules})
    made = pages.withColumns({"host": host_of(F.col(url)), "path": path_of(F.col(url))})
    if not rules:
        return made.withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit("allow")})
    keys = candidates(F.col("host"), F.col("path"), lengths)
    both = {"block": sorted(set(block)), "allow": sorted(set(allow) - set(block))}
    if listed_join:
        listed = spark.createDataFrame([(r, v) for v, rs in both.items() for r in rs], "rule string, kind string")
        key = ["__row"]
        rows = store(made.withColumn("__row", F.expr("uuid()")), "rows")
        found = rows.select("__row", F.posexplode(keys).alias("__at", "rule")).join(listed, "rule").groupBy(*key).agg(F.min_by(F.struct("rule", "kind"), "__at").alias("__hit"))
        return rows.join(found, "__row", "left").withColumns({"rule": F.col("__hit.rule"), "verdict": F.coalesce("__hit.kind", F.lit("allow"))}).drop("__row", "__hit")
    universe = made.select(F.explode(keys).alias("key"))
    held = {v: cascade(universe, spark.sql("select explode(split(:rules, '\n')) as key", {"rules": "\n".join(rs)})) for v, rs in both.items() if rs}
    # a lambda cannot hold a subquery, so the bits become columns for as long as the row is judged
    return _first_listed(made.withColumn("__keys", keys), held)


def _first_listed(made: DataFrame, held: dict[str, Cascade]) -> DataFrame:
    words = {(v, i): f"__{v}{i}" for v, c in held.items() for i in range(len(c.levels))}
    made = made.withColumns({words[v, i]: level.bits.scalar() for v, c in held.items() for i, level in enumerate(c.levels)})

    def member(v: str, key: Column) -> Column:
        found = F.lit(len(held[v].levels) % 2 == 1)
        for depth in range(len(held[v].levels), 0, -1):
            level = held[v].levels[depth - 1]
            has = F.lit(True)
            for place in _places(key, level.words, level.seed):
                has &= F.getbit(F.get(F.col(words[v, depth - 1]), F.floor(place / 64).cast("int")), (place % 64).cast("int")) == 1
            found = F.when(has, found).otherwise(F.lit(depth % 2 == 0))
        return found

    kind = lambda key: F.coalesce(*[F.when(member(v, key), F.lit(v)) for v in held], F.lit(None).cast("string"))
    made = made.withColumn("rule", F.get(F.filter("__keys", lambda k: kind(k).isNotNull()), F.lit(0)))
    return made.withColumn("verdict", F.coalesce(kind(F.col("rule")), F.lit("allow"))).drop("__keys", *words.values())


#: The rules of the registered query.
BLOCK = ["com/en/", "example.net/de/8", "org/es/"]
ALLOW = ["example.com/en/7", "net/de/"]


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge(pages, BLOCK, ALLOW).select("page_id", "host", "path", "rule", "verdict")


OP1_SQL = r"""
with parts as (
  select page_id,
         translate(coalesce(regexp_extract(url, '://([^/?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
         coalesce(regexp_extract(url, '://[^/?#]*([^?#]*)', 1), '') as path
  from pages),
rules(rule, rule_host, rule_path, kind) as (values
  ('com/en/', 'com', '/en/', 'block'), ('net/de/', 'net', '/de/', 'allow'), ('org/es/', 'org', '/es/', 'block'),
  ('example.com/en/7', 'example.com', '/en/7', 'allow'), ('example.net/de/8', 'example.net', '/de/8', 'block')),
judged as (
  select page_id, host, path,
         (select max_by(rule, length(rule)) from rules where (host = rule_host or ends_with(host, '.' || rule_host)) and starts_with(path, rule_path)) as rule
  from parts)
select page_id, host, path, judged.rule as rule, coalesce(kind, 'allow') as verdict
from judged left join rules on judged.rule = rules.rule
"""
