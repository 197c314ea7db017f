"""Operator 8, URL filters: a cascade of Bloom filters over the corpus's complete key universe. DataFrame functions only.

Keys are the hosts of all pages and all their parent domains. Level 1 holds the listed keys; level 2 the other keys of
the universe that level 1 takes for listed; level 3 the listed keys that level 2 takes for unlisted, and so on until a
level has no false positive. For a key of the universe the first level that doesn't hold it decides, so membership is
exact, and pages are judged by an expression over literal bit arrays, with no join. The arrays' size follows the listed
keys that occur, not the pages. Where they would be over ``MOST_BITS``, keys are dealt to parts by hash, each with a cascade of its
own, and the pages are judged part after part, so that no plan carries more.

Rules (host, path, verdict) come first: a rule fits its host and all subdomains if the url's path starts with the rule's
path, and the longest host and path wins. Null urls and urls without ``://`` have an empty host and path, which no rule
fits and no list holds, so they are allowed. Repeated rows are judged alike. An empty table gives an empty result.
"""

from __future__ import annotations

import math
import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsig.llm import shared

RULES = (("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block"))
#: Domains that the query blocks, with their subdomains, where no rule fits.
LISTED = tuple(f"{name}.example.{end}" for name in ("adult-x", "ads-track", "casino-win", "cheap-pills", "free-bets", "spam-farm") for end in ("com", "net", "org"))
#: Bits of all levels together that are sent with a plan (16 MB).
MOST_BITS = 1 << 27


def host_and_path(url: Column) -> tuple[Column, Column]:
    rest = F.when(F.locate("://", url) > 0, url.substr(F.locate("://", url) + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest.substr(F.length(host) + 1, F.length(rest)), r"^[^?#]*", 0)
    return F.translate(host, string.ascii_uppercase, string.ascii_lowercase), path


def with_parents(host: Column) -> Column:
    """The host and its parent domains."""
    labels = F.split(host, r"\.")
    return F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels) - i + 1), "."))


class Level:
    """One Bloom filter: bits in 64-bit words, tested by keyed hashes."""

    def __init__(self, number: int, n: int, rate: float):
        self.number = number
        self.bits = max(64, math.ceil(-n * math.log(rate) / math.log(2) ** 2))
        self.hashes = max(1, round(-math.log2(rate)))
        self.words: list[int] = []

    def places(self, key: Column) -> list[Column]:
        return [F.pmod(F.xxhash64(key, F.lit(self.number), F.lit(i)), F.lit(self.bits)) for i in range(self.hashes)]

    def fill(self, keys: DataFrame) -> None:
        """Or of the keys' bits by word, pre-aggregated by task; the result is as large as the filter."""
        bit = F.explode(F.array(*self.places(F.col("key")))).alias("bit")
        words = keys.select(bit).select(F.floor(F.col("bit") / 64).alias("word"), F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("bit") % 64).cast("int")).alias("mask"))
        self.words = [0] * -(-self.bits // 64)
        for r in words.groupBy("word").agg(F.bit_or("mask").alias("mask")).collect():
            self.words[r["word"]] = r["mask"]

    def holds(self, key: Column) -> Column:
        array = F.split(F.lit(",".join(map(str, self.words))), ",").cast("array<bigint>")  # constant, folded once
        tests = [F.call_function("shiftright", F.get(array, F.floor(p / 64).cast("int")), (p % 64).cast("int")).bitwiseAND(F.lit(1).cast("long")) == 1 for p in self.places(key)]
        out = tests[0]
        for t in tests[1:]:
            out = out & t
        return out


class Cascade:
    """Exact membership for the keys of the universe that it was built over."""

    def __init__(self, levels: list[Level]):
        self.levels = levels

    @property
    def bits(self) -> int:
        return sum(x.bits for x in self.levels)

    def holds(self, key: Column) -> Column:
        out = F.lit(len(self.levels) % 2 == 1)
        for i, level in reversed(list(enumerate(self.levels))):
            out = F.when(~level.holds(key), F.lit(i % 2 == 1)).otherwise(out)
        return out


def first_rate(n_in: int, n_out: int) -> float:
    """The first level's rate of false positives, at which the levels together are small."""
    return min(0.5, math.sqrt(0.5) * n_in / max(1, n_out)) if n_in else 0.5


def build_cascade(universe: DataFrame) -> Cascade:
    """Over (key, listed), keys distinct."""
    counts = {r["listed"]: r["count"] for r in universe.groupBy("listed").count().collect()}
    inside, outside = universe.where("listed").select("key"), universe.where("not listed").select("key")
    n_in, n_out = counts.get(True, 0), counts.get(False, 0)
    levels: list[Level] = []
    rate = first_rate(n_in, n_out)
    while n_in:
        level = Level(len(levels) + 1, n_in, rate)
        level.fill(inside)
        levels.append(level)
        taken, _ = shared.settle(outside.where(level.holds(F.col("key"))), "url-level")
        inside, outside = taken, inside
        n_in, rate = inside.count(), 0.5
    return Cascade(levels)


def parts_of(universe: DataFrame) -> int:
    """How many cascades keep each under MOST_BITS, the later levels taken as large as the first and a half."""
    counts = {r["listed"]: r["count"] for r in universe.groupBy("listed").count().collect()}
    n_in, n_out = counts.get(True, 0), counts.get(False, 0)
    return max(1, math.ceil(2.5 * Level(1, n_in, first_rate(n_in, n_out)).bits / MOST_BITS))


def _rule(host: Column, path: Column, rules) -> tuple[Column, Column]:
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for h, p, v in sorted(rules, key=lambda r: len(r[0]) + len(r[1])):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        name, verdict = F.when(fits, F.lit(h + p)).otherwise(name), F.when(fits, F.lit(v)).otherwise(verdict)
    return name, verdict


def url_filter(pages: DataFrame, listed: DataFrame, rules=RULES) -> DataFrame:
    """page_id, host, path, listed, rule and verdict of each row of ``pages``; ``listed`` (key) holds blocked domains."""
    host, path = host_and_path(F.col("url"))
    rows = pages.select("page_id", host.alias("host"), path.alias("path"))
    hosts = rows.where("host <> ''").select("host").distinct()
    keys = hosts.select(F.explode(with_parents(F.col("host"))).alias("key")).distinct()
    low = F.translate("key", string.ascii_uppercase, string.ascii_lowercase)
    marks = listed.where("key is not null").select(low.alias("key")).distinct().withColumn("mark", F.lit(True))
    universe, _ = shared.settle(keys.join(marks, "key", "left").select("key", F.coalesce("mark", F.lit(False)).alias("listed")), "url-keys")
    parts = parts_of(universe)
    rows = rows.withColumn("listed", F.lit(False))
    for i in range(parts):
        mine = lambda key: F.pmod(F.xxhash64(key, F.lit(77)), F.lit(parts)) == i  # noqa: E731, B023
        cascade = build_cascade(universe.where(mine(F.col("key"))) if parts > 1 else universe)
        if not cascade.levels:
            continue
        held = (lambda key: mine(key) & cascade.holds(key)) if parts > 1 else cascade.holds  # noqa: B023
        rows = rows.withColumn("listed", F.col("listed") | ((F.col("host") != "") & F.exists(with_parents(F.col("host")), held)))
        if parts > 1:
            rows, _ = shared.settle(rows, "url-part")
    rule, verdict = _rule(F.col("host"), F.col("path"), rules)
    return rows.select("page_id", "host", "path", "listed", rule.alias("rule"), F.coalesce(verdict, F.when(F.col("listed"), "block").otherwise("allow")).alias("verdict"))
