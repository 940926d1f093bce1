"""URL filters by a Bloom filter cascade, with DataFrame functions only.

A rule is `host/path-prefix` with a verdict. It fits its host and all subdomains where the path starts with
the rule's; the longest fitting rule wins. For every url the possible keys are each host suffix joined with the
path prefix of each length that occurs among the rules. Those keys, over all pages, are the complete key universe.

Level 0 of the cascade is a Bloom filter of the listed keys. Level 1 encodes the keys of the universe that level 0
lets through wrongly, level 2 the listed keys that level 1 lets through, and so on until nothing is wrong. A key of
the universe is listed exactly if the first level that rejects it is odd-numbered (or, past the last level, by its
parity), so queries need no join with the list. The levels hold bits in proportion to the list, not to the pages:
the list is bounded by MAX_LISTED, which is checked.

Results for odd input: a null url or one without `://` has an empty host and path and the default verdict; an empty
table gives an empty result; repeated rows are judged alike; a null page_id is kept; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import discard, materialize

HASHES = 4
BITS_PER_KEY = 10
MAX_LISTED = 1_000_000  # 10 Mbit at level 0: bounds what is held on the driver and sent to executors


@dataclass(frozen=True)
class Rule:
    verdict: str
    key: str  # host, then the path prefix from its first slash on

    @property
    def path(self) -> str:
        return self.key[self.key.index("/") :]


@dataclass(frozen=True)
class Level:
    number: int
    bits: int
    words: tuple[int, ...]

    def passes(self, key: Column) -> Column:
        held = F.split(F.lit(",".join(map(str, self.words))), ",").cast("array<bigint>")  # folded to a constant
        out = F.lit(True)
        for p in _positions(key, self.number, self.bits):
            out = out & (F.getbit(F.element_at(held, (F.shiftright(p, 6) + 1).cast("int")), F.pmod(p, F.lit(64)).cast("int")) == 1)
        return out


def _positions(key: Column, level: int, bits: int) -> list[Column]:
    return [F.pmod(F.xxhash64(key, F.lit(level * HASHES + i)), F.lit(bits)) for i in range(HASHES)]


def build_level(keys: DataFrame, number: int, count: int) -> Level:
    """A Bloom filter of the column `key`; its words are OR-ed together per word before they leave the executors."""
    bits = max(64, -(-count * BITS_PER_KEY // 64) * 64)
    spots = keys.select(F.explode(F.array(*_positions(F.col("key"), number, bits))).alias("p"))
    words = spots.groupBy(F.shiftright("p", 6).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(pmod(p, 64) as int))")).alias("b"))
    held = [0] * (bits // 64)
    for row in words.collect():
        held[row.w] = row.b
    return Level(number, bits, tuple(held))


def build_cascade(listed: DataFrame, universe: DataFrame) -> list[Level]:
    """Levels that tell the listed keys from all others of the universe. Both frames have a distinct column `key`."""
    n = listed.count()
    if n > MAX_LISTED:
        raise ValueError(f"{n} listed keys; a filter that goes to every executor is bounded to {MAX_LISTED}")
    levels: list[Level] = []
    encoded, others, count = listed, universe.join(listed, "key", "left_anti"), n
    scratch: list[DataFrame] = []
    while count:
        level = build_level(encoded, len(levels), count)
        levels.append(level)
        passed = materialize(others.where(level.passes(F.col("key"))), "cascade")
        scratch.append(passed)
        encoded, others, count = passed, encoded, passed.count()
    discard(*scratch)
    return levels


def is_listed(key: Column, levels: list[Level]) -> Column:
    """Exact membership for keys of the universe: the parity of the first level that rejects the key."""
    out = F.lit(len(levels) % 2 == 1)
    for level in reversed(levels):
        out = F.when(~level.passes(key), F.lit(level.number % 2 == 1)).otherwise(out)
    return out


def split_url() -> tuple[Column, Column]:
    """(host, path) of the column `url`. The host is what follows the first `://` up to `/`, `?`, `#` or the end, with A-Z lower-cased."""
    rest = F.when(F.instr("url", "://") > 0, F.expr("substring(url, instr(url, '://') + 3)")).otherwise(F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return host, path


def candidate_keys(host: Column, path: Column, rules: list[Rule]) -> Column:
    """Array of (key, length) a url could be listed under: host suffixes at label borders times path prefixes."""
    labels = F.split(host, r"\.", -1)
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    lengths = sorted({len(r.path) for r in rules})
    fitting = F.filter(F.array(*map(F.lit, lengths)), lambda n: n <= F.length(path))
    return F.flatten(F.transform(suffixes, lambda s: F.transform(fitting, lambda n: F.concat(s, F.substring(path, F.lit(1), n)))))


def judge_urls(pages: DataFrame, rules: list[Rule], default: str = "allow") -> DataFrame:
    """pages (page_id, url) -> page_id, host, path, rule, verdict."""
    split = pages.select("page_id", F.col("url").cast("string").alias("url"))
    host, path = split_url()
    split = split.select("page_id", F.coalesce(host, F.lit("")).alias("host"), F.coalesce(path, F.lit("")).alias("path"))
    keys = split.withColumn("keys", candidate_keys(F.col("host"), F.col("path"), rules))
    universe = materialize(keys.select(F.explode("keys").alias("key")).distinct(), "universe")
    spark = pages.sparkSession
    cascades = {}
    for verdict in ("allow", "block"):
        listed = spark.createDataFrame([(r.key,) for r in rules if r.verdict == verdict], "key string")
        cascades[verdict] = build_cascade(listed, universe)
    discard(universe)

    def longest(verdict: str) -> Column:
        fitting = F.filter("keys", lambda k: is_listed(k, cascades[verdict]))
        return F.aggregate(fitting, F.lit(None).cast("string"), lambda a, k: F.when(a.isNull() | (F.length(k) > F.length(a)), k).otherwise(a))

    judged = keys.select("page_id", "host", "path", longest("allow").alias("a"), longest("block").alias("b"))
    rule = F.when(F.length("a") >= F.coalesce(F.length("b"), F.lit(0)), F.col("a")).otherwise(F.col("b"))
    by_rule = F.when(rule == F.col("a"), "allow").when(rule.isNotNull(), "block")
    return judged.select("page_id", "host", "path", rule.alias("rule"), F.coalesce(by_rule, F.lit(default)).alias("verdict"))
