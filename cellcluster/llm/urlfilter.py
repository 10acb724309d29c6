"""URL filter: rules by host and path, and a logistic regression on hashed
character n-grams of both for the rest. Everything that touches the table of
pages is an SQL expression; the model is fitted by the driver on a labelled
table of a few hundred addresses, whose features come from the same expressions.
"""

from __future__ import annotations

import json
import math
from itertools import product

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

SLOTS = 8192
ORDERS = (3, 4, 5)
#: Most labelled addresses that the driver takes.
MAX_LABELLED = 50_000

#: Production rules: verdict, host, start of the path.
RULES = (("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/"))

# words of hosts, for the labelled table below
_UNWANTED = ("casino", "bets", "pills", "adult", "spam", "ads", "track", "porn", "poker", "viagra", "loans", "xxx", "slots", "warez", "clickbait", "jackpot", "free", "cheap", "win", "farm")
_WANTED = ("garden", "library", "science", "river", "museum", "kitchen", "weather", "history", "school", "travel", "music", "mountain", "theater", "theory", "nation", "station", "bread", "whether", "thread", "north")
_PREFIX, _ZONE, _LANG = ("", "www.", "m.", "blog."), ("example.com", "example.net", "example.org"), ("en", "de", "fr", "es")


def labelled_urls() -> list[tuple[str, int]]:
    """A few hundred addresses by rule, 1 for unwanted: zone, prefix and path say nothing about the label."""
    out = []
    for label, words in ((1, _UNWANTED), (0, _WANTED)):
        for k, (a, step) in enumerate(product(range(len(words)), (1, 3, 7))):
            host = f"{words[a]}-{words[(a + step) % len(words)]}" if k % 3 else words[a]
            out.append((f"https://{_PREFIX[k % 4]}{host}.{_ZONE[k % 3]}/{_LANG[k // 3 % 4]}/{k * 37 % 9973}", label))
    syllables = ("th", "tion", "er", "an", "the", "on", "ing", "ble", "re", "nd", "st", "en", "ou", "ha", "ly", "es")
    for k in range(160):
        host = syllables[k % 16] + syllables[k * 5 % 16] + syllables[k // 4 % 16]
        out.append((f"http://{_PREFIX[k % 4]}{host}.{_ZONE[k % 3]}/{_LANG[k // 3 % 4]}/{k * 53 % 9973}", 0))
    return out


def host_of(url: Column) -> Column:
    """From the first :// up to /, ?, # or the end, A-Z lower-cased; empty if there is none."""
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    """What follows the host up to ?, # or the end."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def fitting_rule(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule of a short list that fits, as struct(length, rule, verdict); null if none. Of equal rules a block wins.

    A rule fits its host and all subdomains, if the path starts with the rule's.
    """
    if not rules:
        return F.lit(None).cast("struct<length:int,rule:string,verdict:string>")
    fits = [
        F.when(((host == h) | host.endswith(f".{h}")) & path.startswith(p), F.struct(F.lit(len(h) + len(p)).alias("length"), F.lit(h + p).alias("rule"), F.lit(v).alias("verdict")))
        for v, h, p in rules
    ]
    return F.array_max(F.array(*fits))


def gram_slots(host: Column, path: Column, slots: int = SLOTS) -> Column:
    """Slots of the n-grams of ^host$ and ^path$; each part is hashed with its own seed."""
    def grams(seed: str, part: Column, n: int) -> Column:
        marked = F.concat(F.lit("^"), part, F.lit("$"))
        starts = F.sequence(F.lit(1), F.greatest(F.length(marked) - n + 1, F.lit(1)))
        found = F.transform(starts, lambda i: F.pmod(F.xxhash64(F.lit(seed), F.substr(marked, i, F.lit(n))), F.lit(slots)).cast("int"))
        return F.when(F.length(part) > 0, found).otherwise(F.array().cast("array<int>"))

    parts = [grams(seed, part, n) for seed, part in (("h", host), ("p", path)) for n in ORDERS]
    return F.concat(*parts)


def fit(spark: SparkSession, labelled: list[tuple[str, int]] | None = None, slots: int = SLOTS, epochs: int = 60, rate: float = 0.5, decay: float = 1e-4) -> list[float]:
    """Weights, the last one the bias; plain stochastic descent over a small table, in a fixed order."""
    rows = labelled_urls() if labelled is None else labelled
    if len(rows) > MAX_LABELLED:
        raise ValueError(f"the driver fits at most {MAX_LABELLED} addresses; pass a sample")
    if not rows:
        return [0.0] * slots + [-1.0]
    quote = lambda s: "'" + s.replace("\\", "\\\\").replace("'", "\\'") + "'"
    known = spark.sql("SELECT * FROM VALUES " + ", ".join(f"({k}, {quote(u)}, {int(y)})" for k, (u, y) in enumerate(rows)) + " AS t(k, url, label)")
    seen = known.select("k", "label", gram_slots(host_of(F.col("url")), path_of(F.col("url")), slots).alias("grams")).orderBy("k").collect()
    w, bias = [0.0] * slots, 0.0
    for epoch in range(epochs):
        step = rate / (1 + 0.05 * epoch)
        for row in seen:
            x = 1 / math.sqrt(max(1, len(row.grams)))
            p = 1 / (1 + math.exp(-max(-35.0, min(35.0, bias + x * sum(w[g] for g in row.grams)))))
            g = step * (p - row.label)
            bias -= g * 0.1
            for s in set(row.grams):
                w[s] -= g * x * 1.0 + step * decay * w[s]
    return [round(v, 5) for v in w] + [round(bias, 5)]


def unwanted(host: Column, path: Column, weights: list[float]) -> Column:
    """Probability that an address is unwanted; an address without host and path has the bias alone."""
    known = F.from_json(F.lit(json.dumps(weights)), "array<double>")  # a constant of the plan
    grams = gram_slots(host, path, len(weights) - 1)
    total = F.aggregate(grams, F.lit(0.0), lambda acc, g: acc + F.get(known, g))
    return 1 / (1 + F.exp(-(F.lit(weights[-1]) + total / F.sqrt(F.greatest(F.size(grams), F.lit(1))))))


def judge_urls(pages: DataFrame, weights: list[float], url: str = "url", rules=RULES, threshold: float = 0.5) -> DataFrame:
    """``pages`` with host, path, rule, unwanted and verdict.

    A rule decides where one fits, else the model blocks from ``threshold`` on.
    Null and addresses without :// have empty parts, fit no rule with a host,
    and the model has nothing but its bias for them, which is the same for all.
    Addresses of any length are read whole. Each row is judged by itself, so
    repeated rows agree; an empty table gives no row; columns of ``pages`` with
    the names of the results are replaced.
    """
    made = ("host", "path", "rule", "unwanted", "verdict")
    address = F.col(f"`{url}`").cast("string")
    kept = [c for c in pages.columns if c not in made]
    out = pages.select(F.struct(*[F.col(f"`{c}`") for c in kept]).alias("row"), host_of(address).alias("host"), path_of(address).alias("path"))
    host, path = F.col("host"), F.col("path")
    out = out.select("row", "host", "path", fitting_rule(host, path, rules).alias("fit"), unwanted(host, path, weights).alias("unwanted"))
    verdict = F.coalesce(F.col("fit.verdict"), F.when(F.col("unwanted") >= threshold, "block").otherwise("allow"))
    return out.select("row.*", "host", "path", F.col("fit.rule").alias("rule"), "unwanted", verdict.alias("verdict"))


def op5_url_ngrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return judge_urls(pages, fit(spark)).select("page_id", "host", "path", "rule", "verdict", "unwanted")
