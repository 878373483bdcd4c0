"""URL filters: host and path rules, and a logistic regression on hashed character n-grams for all other urls.

Everything is built from DataFrame functions. Host: after the first `://` up to `/`, `?`, `#` or the end, A-Z
lower-cased; path: from there up to `?`, `#` or the end; urls without `://` have neither. A rule `host/path` fits its
host and all subdomains where the url's path starts with the rule's; the longest rule that fits wins (of equally long
ones that with the longer host).

The model: every n-gram (n in `GRAMS`) of `^host$path` is hashed into `BUCKETS`; a url's features are its distinct
buckets, each 1 / sqrt(number of them). Weights come from full-batch gradient descent, one aggregate a step over a
small labelled url table of at most `MAX_LABELLED` urls (`labelled_urls` takes those that rules decide, by hash order);
the driver holds only the `BUCKETS` weights.

Null urls and urls without `://` have empty host and path; no rule fits them and they score by the
model like any other; repeated rows are judged by themselves; with no labelled url, or with one label only, the weights
are zero but for a bias towards that label (none: allow); empty tables give empty results; other columns pass through, but those named like what is given out
(host, path, rule, verdict, score), which are replaced.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))
GRAMS = (3, 4, 5)
BUCKETS = 4096
MAX_LABELLED = 4096
STEPS = 40
RATE = 4.0
SHRINK = 1e-4


def split_url(df: DataFrame, url: str = "url") -> DataFrame:
    """df with host and path."""
    u = F.coalesce(F.col(f"`{url}`"), F.lit(""))
    at = F.instr(u, "://")
    rest = F.when(at > 0, u.substr(at + 3, F.length(u))).otherwise("")
    host = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)
    return df.withColumn("host", F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")).withColumn("path", path)


def rule_for(host: Column, path: Column, rules=RULES) -> Column:
    """struct(rule, verdict) of the longest rule that fits; null if none does."""
    fits = [
        F.when(((host == h) | host.endswith(f".{h}")) & path.startswith(p), F.struct(F.lit(len(h + p)).alias("n"), F.lit(len(h)).alias("m"), F.lit(h + p).alias("rule"), F.lit(v).alias("verdict")))
        for h, p, v in rules
    ]
    return F.greatest(*fits, F.lit(None).cast("struct<n:int,m:int,rule:string,verdict:string>")) if fits else F.lit(None).cast("struct<n:int,m:int,rule:string,verdict:string>")


def features(host: Column, path: Column) -> Column:
    """Distinct buckets of the character n-grams."""
    text = F.concat(F.lit("^"), host, F.lit("$"), path)
    grams = [F.transform(F.sequence(F.lit(1), F.greatest(F.length(text) - (n - 1), F.lit(1))), lambda i, n=n: F.pmod(F.xxhash64(F.substr(text, i, F.lit(n))), F.lit(BUCKETS)).cast("int")) for n in GRAMS]
    return F.array_distinct(F.concat(*grams))


def _weights(values: list[float]) -> Column:
    """The weights as one constant of the plan."""
    return F.from_json(F.lit("[" + ",".join(repr(float(v)) for v in values) + "]"), "array<double>")


def _logit(grams: Column, weights: Column, bias: float) -> Column:
    total = F.aggregate(grams, F.lit(0.0), lambda s, i: s + F.get(weights, i))
    return F.lit(float(bias)) + total / F.sqrt(F.size(grams).cast("double"))


def labelled_urls(urls: DataFrame, rules=RULES, limit: int = MAX_LABELLED) -> DataFrame:
    """A small table host, path, y (1: block): distinct urls that a rule decides, at most `limit`, in hash order."""
    ruled = urls.withColumn("_rule", rule_for(F.col("host"), F.col("path"), rules)).filter("_rule is not null")
    ruled = ruled.select("host", "path", (F.col("_rule.verdict") == "block").cast("int").alias("y")).distinct()
    return ruled.orderBy(F.xxhash64("host", "path"), "host", "path").limit(limit)


def train(labelled: DataFrame, *, steps: int = STEPS, rate: float = RATE, shrink: float = SHRINK) -> tuple[float, list[float]]:
    """Bias and weights. labelled: host, path, y (0 or 1). Labels weigh alike in sum."""
    rows = labelled.select(features(F.col("host"), F.col("path")).alias("grams"), "y").cache()
    counts = {r["y"]: r["n"] for r in rows.groupBy("y").agg(F.count("*").alias("n")).collect()}
    weights, momentum, bias, bias_momentum = [0.0] * BUCKETS, [0.0] * BUCKETS, 0.0, 0.0
    if len(counts) < 2:
        rows.unpersist()
        return ({0: -1.0, 1: 1.0}.get(next(iter(counts), 0), -1.0)), weights
    total = sum(counts.values())
    share = F.when(F.col("y") == 1, F.lit(total / 2 / counts[1])).otherwise(F.lit(total / 2 / counts[0]))
    for _ in range(steps):
        p = 1 / (1 + F.exp(-_logit(F.col("grams"), _weights(weights), bias)))
        slope = rows.select("grams", ((p - F.col("y")) * share / total).alias("d"))
        each = slope.select("d", F.size("grams").alias("n"), F.explode(F.concat(F.array(F.lit(-1)), "grams")).alias("bucket"))
        sums = each.groupBy("bucket").agg(F.sum(F.when(F.col("bucket") < 0, F.col("d")).otherwise(F.col("d") / F.sqrt(F.col("n").cast("double")))).alias("g")).collect()
        gradient = {r["bucket"]: r["g"] for r in sums}
        bias_momentum = 0.9 * bias_momentum - rate * gradient.pop(-1, 0.0)
        bias += bias_momentum
        for i in range(BUCKETS):
            momentum[i] = 0.9 * momentum[i] - rate * (gradient.get(i, 0.0) * 16 + shrink * weights[i])
            weights[i] += momentum[i]
    rows.unpersist()
    if not all(map(math.isfinite, weights)):
        raise ArithmeticError("the descent left the finite numbers; lower the rate")
    return bias, weights


def judge(pages: DataFrame, *, url: str = "url", rules=RULES, model: tuple[float, list[float]] | None = None) -> DataFrame:
    """pages with host, path, rule, verdict and score (the model's probability of block)."""
    names, new = pages.columns, ("host", "path", "rule", "verdict", "score")
    inner = pages.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)])
    urls = split_url(inner, f"c{names.index(url)}")
    model = model or train(labelled_urls(urls.select("host", "path"), rules))
    fit = rule_for(F.col("host"), F.col("path"), rules)
    score = 1 / (1 + F.exp(-_logit(features(F.col("host"), F.col("path")), _weights(model[1]), model[0])))
    out = urls.withColumn("_fit", fit).withColumn("score", score)
    verdict = F.coalesce(F.col("_fit.verdict"), F.when(F.col("score") >= 0.5, "block").otherwise("allow"))
    return out.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(names) if c not in new], "host", "path", F.col("_fit.rule").alias("rule"), verdict.alias("verdict"), "score")


def report(pages: DataFrame) -> DataFrame:
    return judge(pages.select("page_id", "url")).select("page_id", "host", "path", "rule", "verdict", "score")
