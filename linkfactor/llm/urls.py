"""URL filters: longest-match rules, and exact list membership by a cascade of Bloom filters.

The cascade knows the complete set of keys of the corpus. Its first filter holds the listed
keys, the second those unlisted keys that pass the first, the third the listed keys that
pass the second, and so on until no key passes wrongly. A key's answer is the parity of the
first filter that it fails, which is exact for every key of the corpus; probing joins
nothing, as each filter is one array of longs that a scalar subquery puts into the plan.

The first filter's rate of false positives is at most the share of listed keys, so all later
levels are no larger than the list, however large the corpus. A list whose filters would take
more than WORD_LIMIT longs is cut into shards by a hash of the key, each with a cascade of
its own that sees the rows of its shard only; so a plan never holds more than that.

Defined results: a null url, or one without ``://``, has an empty host and path; an empty
key is looked up like any other; an empty table gives an empty result; an empty list lists
nothing; repeated keys count once; extra columns are left alone.
"""

from __future__ import annotations

from functools import reduce
from math import ceil

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import bloom
from .cluster import settle

#: (host, path prefix, verdict); a rule holds for the host and all subdomains.
RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))
FALSE_POSITIVES = 0.05
#: Longs in one filter at most (8 MB), and bits that a listed key may take there at most.
WORD_LIMIT, KEY_BITS = 1 << 20, 48
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def url_host(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(_rest(url), r"(?s)^([^/?#]*)", 1), _UPPER, _LOWER), F.lit(""))


def _rest(url: Column) -> Column:
    """What follows the first ``://``; null if there is none."""
    return F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1))


def url_path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(_rest(url), r"(?s)^[^/?#]*(/[^?#]*)", 1), F.lit(""))


def best_rule(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """Text and verdict of the longest rule that fits, by length of host and path, then of host; null if none."""
    text = verdict = None
    for name, prefix, said in sorted(rules, key=lambda r: (-len(r[0] + r[1]), -len(r[0]), r[0], r[1])):
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(prefix)
        text = F.when(fits, name + prefix) if text is None else text.when(fits, name + prefix)
        verdict = F.when(fits, said) if verdict is None else verdict.when(fits, said)
    none = F.lit(None).cast("string")
    return (none, none) if text is None else (text, verdict)


def shard_of(key: Column, shards: int) -> Column:
    return F.pmod(F.xxhash64(F.lit("shard"), key), F.lit(shards)).cast("int")


class Cascade:
    """The filters of one list over one universe of keys, shard by shard: (words, hashes, bits) of each level."""

    def __init__(self, shards: list[list[tuple[DataFrame, int, int]]]) -> None:
        self.shards = shards

    def passes(self, shard: int, level: int, key: Column) -> Column:
        words, hashes, bits = self.shards[shard][level]
        return bloom.passes(words, key, level, hashes, bits)

    def contains(self, shard: int, key: Column) -> Column:
        """Exact for keys of the universe and of the shard."""
        levels = len(self.shards[shard])
        answer = F.lit(levels % 2 == 1)
        for level in reversed(range(levels)):
            answer = F.when(~self.passes(shard, level, key), F.lit(level % 2 == 1)).otherwise(answer)
        return answer

    def is_listed(self, frame: DataFrame, key: Column, name: str) -> DataFrame:
        """frame with the boolean column ``name``; each shard's cascade reads the rows of its shard."""
        if len(self.shards) == 1:
            return frame.withColumn(name, self.contains(0, key))
        parts = [frame.where(shard_of(key, len(self.shards)) == s).withColumn(name, self.contains(s, key)) for s in range(len(self.shards))]
        return reduce(DataFrame.unionByName, parts)


def build_cascade(universe: DataFrame, listed: DataFrame, fpp: float = FALSE_POSITIVES, word_limit: int = WORD_LIMIT) -> Cascade:
    """universe, listed: a column ``key``; listed keys outside the universe are kept too."""
    wanted = settle(listed.select(F.col("key")).where("key is not null").distinct())
    rest = settle(universe.select("key").where("key is not null").distinct().join(wanted, "key", "left_anti"))
    n_wanted, n_rest = wanted.count(), rest.count()
    shards = max(1, ceil(n_wanted * KEY_BITS / 64 / word_limit))
    built = Cascade([[] for _ in range(shards)])
    for shard in range(shards):
        levels = built.shards[shard]
        sides = {True: wanted, False: rest}
        if shards > 1:
            sides = {k: x.where(shard_of(F.col("key"), shards) == shard) for k, x in sides.items()}
        inside, rate = True, min(fpp, max(2.0**-30, n_wanted / max(1, n_rest)))
        while n := sides[inside].count():
            level = len(levels)
            hashes, bits = bloom.sized(n, rate)
            levels.append((settle(bloom.filter_words(sides[inside], level, hashes, bits)), hashes, bits))
            sides[not inside] = settle(sides[not inside].where(built.passes(shard, level, F.col("key"))))
            inside, rate = not inside, fpp
    return built


def judge_urls(pages: DataFrame, listed: DataFrame, rules=RULES, key: str = "page_id", url: str = "url") -> DataFrame:
    """key, host, path, rule and verdict of every page: the rule's verdict, else block for keys (host and path) on the list."""
    parts = pages.select(F.col(key), url_host(F.col(url)).alias("host"), url_path(F.col(url)).alias("path"))
    cascade = build_cascade(parts.select(F.concat("host", "path").alias("key")), listed)
    rule, verdict = best_rule(F.col("host"), F.col("path"), rules)
    marked = cascade.is_listed(parts, F.concat("host", "path"), "on_list")
    return marked.select(key, "host", "path", rule.alias("rule"), F.coalesce(verdict, F.when(F.col("on_list"), "block").otherwise("allow")).alias("verdict"), "on_list")
