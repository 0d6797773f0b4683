"""URL verdicts from path rules and a Bloom filter cascade, in DataFrame functions only.

The cascade holds a list of keys exactly over a closed universe: level 1 encodes the listed keys,
level 2 the unlisted keys of the universe that level 1 lets through, level 3 the listed keys that
level 2 lets through, and so on until a level lets nothing wrong through. A key's membership is the
parity of the first level that stops it, so judging a URL reads literals and needs no join.

Cases: a null url, or one without "://", has an empty host and path and takes the verdict of the
empty key; ties of rules can't be (a rule is its string); repeated rows are judged alike; an empty
table gives no rows; an empty list gives a cascade that lists nothing. A list too large for literals is joined instead.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skewtile.llm.scratch import settle

# The capital letters that hosts fold, and their small ones.
_UPPER, _SMALL = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), _UPPER, _SMALL), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def longest_rule(host: Column, path: Column, rules: list[tuple[str, str]]) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits; both null where none does. rules: (verdict, host and path)."""
    rule = verdict = F.lit(None).cast("string")
    for said, text in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        site, _, rest = text.partition("/")
        fits = ((host == site) | F.endswith(host, F.lit("." + site))) & F.startswith(path, F.lit("/" + rest))
        rule, verdict = F.when(fits, F.lit(text)).otherwise(rule), F.when(fits, F.lit(said)).otherwise(verdict)
    return rule, verdict


@dataclass(frozen=True)
class Level:
    n_bits: int
    n_hashes: int
    seed: int
    bits: bytes

    def _at(self, key: Column, i: int) -> Column:
        return F.pmod(F.xxhash64(key, F.lit(self.seed * 64 + i)), F.lit(self.n_bits))

    def holds(self, key: Column) -> Column:
        data = F.lit(bytearray(self.bits))

        def bit(i: int) -> Column:
            at = self._at(key, i)
            byte = F.conv(F.hex(F.substring(data, F.shiftright(at, 3).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
            return F.shiftright(byte, 0).bitwiseAND(F.shiftleft(F.lit(1), 0) * F.pow(F.lit(2), at % 8).cast("int")) != 0

        return reduce(lambda a, b: a & b, (bit(i) for i in range(self.n_hashes)))


@dataclass(frozen=True)
class Cascade:
    levels: tuple[Level, ...]

    def contains(self, key: Column) -> Column:
        """True for exactly the listed keys, for every key of the universe it was built over."""
        verdict = F.lit(len(self.levels) % 2 == 1)
        for i, level in reversed(list(enumerate(self.levels))):
            verdict = F.when(level.holds(key), verdict).otherwise(F.lit(i % 2 == 1))
        return verdict

    @property
    def n_bytes(self) -> int:
        return sum(len(x.bits) for x in self.levels)


class CascadeTooLarge(ValueError):
    """The list needs more filter bytes than may be sent to every task; judge_listed joins with it then."""


def build_level(keys: DataFrame, n: int, bits_per_key: float, seed: int, most_bytes: int) -> Level:
    n_bits = max(64, 8 * math.ceil(n * bits_per_key / 8))
    if n_bits // 8 > most_bytes:
        raise CascadeTooLarge(f"{n} keys need {n_bits // 8} bytes, {most_bytes} are allowed")
    level = Level(n_bits, max(1, round(bits_per_key * math.log(2))), seed, b"")
    at = F.explode(F.array(*(level._at(F.col("key"), i) for i in range(level.n_hashes))))
    words = keys.select(at.alias("at")).groupBy(F.floor(F.col("at") / 32).cast("int").alias("word"))
    words = words.agg(F.bit_or(F.pow(F.lit(2), F.col("at") % 32).cast("long")).alias("bits"))
    out = bytearray(n_bits // 8 + 4)
    for r in words.toLocalIterator():  # at most n_bits / 32 rows, which is checked above
        out[r["word"] * 4 : r["word"] * 4 + 4] = int(r["bits"]).to_bytes(4, "little")
    return Level(n_bits, level.n_hashes, seed, bytes(out))


def build_cascade(listed: DataFrame, universe: DataFrame, bits_per_key: float = 8.0, most_bytes: int = 16 << 20) -> Cascade:
    """listed, universe: one column of keys each (nulls are no keys). The listed keys join the universe.

    Raises CascadeTooLarge if a level would need over most_bytes."""
    key = lambda df: df.toDF("key").select(F.col("key").cast("string")).where("key is not null")
    both = key(universe).withColumn("listed", F.lit(0)).unionByName(key(listed).withColumn("listed", F.lit(1)))
    both = settle(both.groupBy("key").agg(F.max("listed").alias("listed")), "universe")
    levels: list[Level] = []
    wrong = F.col("listed") == 1
    while n := both.where(wrong).count():
        level = build_level(both.where(wrong).select("key"), n, bits_per_key, len(levels), most_bytes)
        levels.append(level)
        side = F.col("listed") == (0 if len(levels) % 2 else 1)
        wrong = reduce(lambda a, b: a & b, (x.holds(F.col("key")) for x in levels), side)
    return Cascade(tuple(levels))


def _sites(pages: DataFrame) -> DataFrame:
    return pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))


def _judged(sites: DataFrame, rules: list[tuple[str, str]]) -> DataFrame:
    rule, said = longest_rule(F.col("host"), F.col("path"), rules)
    return sites.select("page_id", "host", "path", rule.alias("rule"), "listed", F.coalesce(said, F.when(F.col("listed"), F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"))


def judge_urls(pages: DataFrame, rules: list[tuple[str, str]], cascade: Cascade) -> DataFrame:
    """page_id, host, path, rule, listed, verdict: the longest fitting rule's verdict, else block for listed hosts."""
    return _judged(_sites(pages).withColumn("listed", cascade.contains(F.col("host"))), rules)


def judge_listed(pages: DataFrame, rules: list[tuple[str, str]], listed: DataFrame, universe: DataFrame, **options) -> DataFrame:
    """judge_urls with the cascade of the list; a list that no cascade of the allowed size holds is joined with the pages' distinct hosts."""
    try:
        return judge_urls(pages, rules, build_cascade(listed, universe, **options))
    except CascadeTooLarge:
        sites = _sites(pages)
        bad = sites.select(F.col("host").alias("_host")).distinct().join(listed.toDF("_host").distinct(), "_host", "left_semi")
        sites = sites.join(bad, F.col("host") == F.col("_host"), "left")
        return _judged(sites.select("page_id", "host", "path", F.col("_host").isNotNull().alias("listed")), rules)
