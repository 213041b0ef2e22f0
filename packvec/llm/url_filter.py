"""Operator 3: URL verdicts by rules and, where none fits, by a logistic regression on hashed character n-grams.

The model is trained on a small labelled URL table (at most MAX_LABELLED rows, which bounds the driver's work) and
scores with SQL functions alone: n-grams of host and path are hashed with CRC-32 into a fixed number of weights, a
literal of the plan whose size is a parameter and does not grow with the data.
"""

from __future__ import annotations

import itertools
import math
import zlib
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from packvec.llm.common import LOWER, UPPER

#: Rows of the labelled table that training uses at most; a larger table is refused.
MAX_LABELLED = 5_000
BUCKETS, GRAMS = 1 << 12, (3, 4)

Rule = tuple[str, str, str]  # verdict, host, path


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host: from behind the first :// up to /, ?, # or the end, A-Z lower-cased. Path: then up to ?, # or the end."""
    has = F.instr(url, "://") > 0
    rest = F.substring_index(F.substring_index(F.expr("substring({0}, instr({0}, '://') + 3)".format("`_pv_url`")), "#", 1), "?", 1)
    host = F.translate(F.substring_index(rest, "/", 1), UPPER, LOWER)
    path = F.expr("substring({0}, length(substring_index({0}, '/', 1)) + 1)".format("substring_index(substring_index(substring(`_pv_url`, instr(`_pv_url`, '://') + 3), '#', 1), '?', 1)"))
    return F.when(has, host).otherwise(F.lit("")), F.when(has, path).otherwise(F.lit(""))


def rule_of(host: Column, path: Column, rules: Sequence[Rule]) -> Column:
    """(verdict, rule) of the longest rule that fits, else null. A rule fits its host, all subdomains, and paths that start with its path."""
    out = F.lit(None).cast("struct<verdict:string,rule:string>")
    for verdict, h, p in sorted(rules, key=lambda r: (len(r[1]) + len(r[2]), r[1], r[2])):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        out = F.when(fits, F.struct(F.lit(verdict).alias("verdict"), F.lit(h + p).alias("rule"))).otherwise(out)
    return out


def grams_of(host: str, path: str) -> list[int]:
    text = f"^{host}{path}$"
    return [zlib.crc32(text[i : i + n].encode()) % BUCKETS for n in GRAMS for i in range(len(text) - n + 1)]


def fit(labelled: Sequence[tuple[str, str, int]], epochs: int = 150, rate: float = 4.0, decay: float = 1e-5) -> list[float]:
    """Weights of the buckets and, last, the intercept, for (host, path, blocked) rows: full-batch gradient descent."""
    rows = [(grams_of(h, p), y) for h, p, y in labelled]
    if len(rows) > MAX_LABELLED:
        raise ValueError(f"{len(rows)} labelled rows; at most {MAX_LABELLED} are used")
    w, share = [0.0] * (BUCKETS + 1), sum(y for _, y in rows) / max(1, len(rows))
    worth = {1: 0.5 / max(share, 1e-9), 0: 0.5 / max(1 - share, 1e-9)}  # both classes count alike
    for _ in range(epochs if rows else 0):
        step: dict[int, float] = {}
        for x, y in rows:
            z = w[-1] + sum(w[i] for i in x) / math.sqrt(len(x) or 1)
            g = (1 / (1 + math.exp(-max(-30.0, min(30.0, z)))) - y) * worth[y] / len(rows)
            step[BUCKETS] = step.get(BUCKETS, 0.0) + g
            for i in x:
                step[i] = step.get(i, 0.0) + g / math.sqrt(len(x))
        w = [v * (1 - rate * decay) for v in w[:-1]] + w[-1:]
        for i, g in step.items():
            w[i] -= rate * g
    return [round(v, 9) for v in w]


def score(host: Column, path: Column, weights: Sequence[float]) -> Column:
    """Probability that a URL is to be blocked."""
    text = F.concat(F.lit("^"), host, path, F.lit("$"))
    table = F.split(F.lit(",".join(map(repr, weights[:-1]))), ",").cast("array<double>")

    def hashed(n: int) -> Column:
        ends = F.sequence(F.lit(1), F.greatest(F.length(text) - n + 1, F.lit(1)))
        return F.transform(ends, lambda i: F.when(i + n - 1 <= F.length(text), F.pmod(F.crc32(F.encode(text.substr(i, F.lit(n)), "UTF-8")), F.lit(BUCKETS)).cast("int")))

    parts = [hashed(n) for n in GRAMS]
    grams = F.filter(F.concat(*parts), lambda x: x.isNotNull())
    total = F.aggregate(grams, F.lit(0.0), lambda a, i: a + F.get(table, i))
    z = F.lit(float(weights[-1])) + total / F.sqrt(F.greatest(F.size(grams), F.lit(1)).cast("double"))
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-z))


def sample_labels() -> list[tuple[str, str, int]]:
    """A small labelled table made from word lists: hosts and paths of unwanted and of ordinary sites."""
    unwanted = ("spam-farm", "cheap-pills", "casino-bonus", "free-loans", "hot-singles", "win-prizes", "replica-watches", "click-here", "bet-now", "adult-cams", "miracle-diet", "crypto-double", "warez-keys", "payday-cash")
    stems = ("ther", "tion", "heon", "erin", "and", "ston", "river", "school", "garden", "news", "library", "museum", "recipes", "science", "weather", "travel")
    ordinary = [a + b for a, b in itertools.product(stems[:6], ("an", "th", "re", "ing"))] + list(stems)
    languages, out = ("en", "fr", "de", "es"), []
    for blocked, names in ((1, unwanted), (0, ordinary)):
        for i, name in enumerate(names):
            for k, (prefix, top) in enumerate(itertools.product(("", "www.", "blog."), ("com", "org", "net"))):
                out.append((f"{prefix}{name}.example.{top}", f"/{languages[(i + k) % 4]}/{100 + 37 * i + 11 * k}", blocked))
    return out


def judge(df: DataFrame, rules: Sequence[Rule], labelled: Sequence[tuple[str, str, int]] | None = None, url: str = "url", threshold: float = 0.5) -> DataFrame:
    """df with host, path, rule, verdict and p_block (the method's probability).

    Edge cases: null urls and urls without :// have an empty host and path, fit no rule and are judged by the model;
    repeated rows are judged alike; an empty table gives an empty result. Columns of df with the results' names are
    replaced, others pass through.
    """
    results = ("host", "path", "rule", "verdict", "p_block")
    weights = fit(sample_labels() if labelled is None else labelled)
    named = df.withColumn("_pv_url", F.col(url))
    host, path = host_and_path(F.col("_pv_url"))
    split = named.withColumns({"_pv_host": host, "_pv_path": path})
    ruled = split.withColumns({"_pv_rule": rule_of(F.col("_pv_host"), F.col("_pv_path"), rules), "_pv_p": score(F.col("_pv_host"), F.col("_pv_path"), weights)})
    return ruled.select(
        *[F.col(c) for c in df.columns if c not in results],
        F.col("_pv_host").alias("host"), F.col("_pv_path").alias("path"), F.col("_pv_rule.rule").alias("rule"),
        F.coalesce(F.col("_pv_rule.verdict"), F.when(F.col("_pv_p") >= threshold, "block").otherwise("allow")).alias("verdict"),
        F.col("_pv_p").alias("p_block"),
    )
