"""Cost and accuracy measures."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators.erasure import probabilities


# ---------------------------------------------------------------- probes on the table model


def forget_probes(cooccurring: DataFrame, k: int = 10) -> DataFrame:
    """cooccurring: target, cue, c. The k best cues are asked as they are (fb), the next k as paraphrases (aa), pairs of both together (qa)."""
    at = F.row_number().over(Window.partitionBy("target").orderBy(F.desc("c"), "cue"))
    ranked = cooccurring.withColumn("at", at).filter(F.col("at") <= 2 * k)
    fb = ranked.filter(F.col("at") <= k).select("target", F.lit("fb").alias("kind"), "cue", F.lit(None).cast("string").alias("cue2"))
    aa = ranked.filter(F.col("at") > k).select("target", F.lit("aa").alias("kind"), "cue", F.lit(None).cast("string").alias("cue2"))
    second = ranked.filter(F.col("at") > k).select("target", (F.col("at") - k).alias("at"), F.col("cue").alias("cue2"))
    qa = ranked.filter(F.col("at") <= k).join(second, ["target", "at"]).select("target", F.lit("qa").alias("kind"), "cue", "cue2")
    return fb.unionByName(aa).unionByName(qa)


def probe_scores(params: DataFrame, probes: DataFrame, target_of: Column | None = None) -> DataFrame:
    """probes: target, kind, cue, cue2, ans. Adds model_id and value: p(ans | cue), or with two cues the product of both rows, normalised.

    target_of: the target that a model is of, if each has one (only its own probes are asked then); else every model answers all probes.
    """
    p = probabilities(params).select("model_id", "cue", "ans", "p")
    own = ["target"] if target_of is not None else []
    p = p.withColumn("target", target_of) if own else p
    one = probes.filter("cue2 is null").join(p, ["cue", "ans", *own]).select("model_id", "target", "kind", "cue", "cue2", "ans", F.col("p").alias("value"))
    two = probes.filter("cue2 is not null")
    left = p.withColumnRenamed("ans", "got").join(two.withColumnRenamed("ans", "want"), ["cue", *own]).withColumnRenamed("got", "ans").select("model_id", "target", "kind", "cue", "cue2", "want", "ans", F.col("p").alias("p1"))
    right = p.select("model_id", F.col("cue").alias("cue2"), "ans", F.col("p").alias("p2"))
    both = left.join(right, ["model_id", "cue2", "ans"]).groupBy("model_id", "target", "kind", "cue", "cue2", "want").agg(
        F.sum(F.when(F.col("ans") == F.col("want"), F.col("p1") * F.col("p2"))).alias("hit"), F.sum(F.col("p1") * F.col("p2")).alias("all")
    )
    return one.unionByName(both.select("model_id", "target", "kind", "cue", "cue2", F.col("want").alias("ans"), (F.coalesce("hit", F.lit(0.0)) / F.col("all")).alias("value")))


def grouped_scores(scored: DataFrame) -> DataFrame:
    """Means by model, target and kind, with `all` as the plain mean of the kinds."""
    kinds = scored.groupBy("model_id", "target", "kind").agg(F.avg("value").alias("value"))
    return kinds.unionByName(kinds.groupBy("model_id", "target").agg(F.avg("value").alias("value")).withColumn("kind", F.lit("all")))


# ---------------------------------------------------------------- token scores


def membership_loss(token_scores: DataFrame) -> DataFrame:
    """Mean negative log-likelihood of the records of each split (of each model, if there are several)."""
    of = ["model_id"] if "model_id" in token_scores.columns else []
    by = token_scores.groupBy(*of, "split", "sample_id").agg(F.avg(-F.col("lp_after")).alias("nll"))
    return by.groupBy(*of, "split").agg(F.avg("nll").alias("loss"))


def answer_prob(token_scores: DataFrame) -> DataFrame:
    """Length-normalised probability of the answer of each sample."""
    of = ["model_id"] if "model_id" in token_scores.columns else []
    return token_scores.filter("is_answer").groupBy(*of, "sample_id").agg(F.exp(F.avg("lp_after")).alias("prob"))


def truth_ratio(answers: DataFrame) -> DataFrame:
    """answers: sample_id, is_right, prob. Mean probability of the wrong answers over that of the right one."""
    of = ["model_id"] if "model_id" in answers.columns else []
    return answers.groupBy(*of, "sample_id").agg((F.avg(F.when(~F.col("is_right"), F.col("prob"))) / F.max(F.when(F.col("is_right"), F.col("prob")))).alias("ratio"))


def rouge1_recall(pairs: DataFrame) -> DataFrame:
    """pairs: id, reference, output. Share of the reference's distinct words that the output has."""
    a, b = F.array_distinct(F.split("reference", " ")), F.array_distinct(F.split("output", " "))
    return pairs.select("id", (F.size(F.array_intersect(a, b)) / F.size(a)).alias("recall"))


def lcs_length(a: list, b: list) -> int:
    row = [0] * (len(b) + 1)
    for x in a:
        last = 0
        for j, y in enumerate(b):
            last, row[j + 1] = row[j + 1], last + 1 if x == y else max(row[j + 1], row[j])
    return row[-1]


def rouge_lcs_recall(pairs: DataFrame) -> DataFrame:
    """Longest common subsequence of words over the reference's length."""

    @F.pandas_udf("double")
    def run(reference: pd.Series, output: pd.Series) -> pd.Series:
        return pd.Series([lcs_length(a.split(" "), b.split(" ")) / len(a.split(" ")) for a, b in zip(reference, output, strict=True)])

    return pairs.select("id", run("reference", "output").alias("recall"))


def ks_statistic(rows: DataFrame) -> DataFrame:
    """rows: side (a or b), value. The largest distance of both cumulative distributions, with both sizes."""
    step = lambda s: (F.col("side") == s).cast("long")
    ties = rows.groupBy("value").agg(F.sum(step("a")).alias("a"), F.sum(step("b")).alias("b"))
    w = Window.orderBy("value").rowsBetween(Window.unboundedPreceding, 0)  # distinct values of two small samples of scores
    run = ties.select(F.sum("a").over(w).alias("a"), F.sum("b").over(w).alias("b"))
    total = rows.agg(F.sum(step("a")).alias("na"), F.sum(step("b")).alias("nb"))
    return run.crossJoin(F.broadcast(total)).groupBy("na", "nb").agg(F.max(F.abs(F.col("a") / F.col("na") - F.col("b") / F.col("nb"))).alias("d"))


def ks_p_value(d: float, na: int, nb: int) -> float:
    """Asymptotic two-sided p-value."""
    root = math.sqrt(na * nb / (na + nb))
    x = (root + 0.12 + 0.11 / root) * d
    if x < 0.2:
        return 1.0
    return max(0.0, min(1.0, 2 * sum((-1) ** (k - 1) * math.exp(-2 * k * k * x * x) for k in range(1, 101))))


def ks_quality(rows: DataFrame) -> DataFrame:
    """rows: model_id, value, side (a: the model, b: its reference, in every model). d and p (two-sided, asymptotic) of each model: how far it is from the reference.

    One model's scores are a few hundred numbers and meet in one task; the tables of many models spread.
    """

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        a, b = (sorted(frame.loc[frame["side"] == s, "value"].round(9)) for s in "ab")
        d = max((abs(sum(x <= v for x in a) / len(a) - sum(x <= v for x in b) / len(b)) for v in {*a, *b}), default=0.0) if a and b else float("nan")
        return pd.DataFrame({"model_id": [frame["model_id"].iloc[0]], "d": [d], "p": [ks_p_value(d, len(a), len(b)) if a and b else float("nan")]})

    return rows.select("model_id", "side", "value").groupBy("model_id").applyInPandas(run, "model_id string, d double, p double")


def model_utility(scores: DataFrame) -> DataFrame:
    """scores: model_id, split, value -> harmonic mean of the splits (0 if one is 0)."""
    return scores.groupBy("model_id").agg((F.when(F.min("value") > 0, F.count("*") / F.sum(1 / F.col("value"))).otherwise(0.0)).alias("utility"))


def ngram_entropy(texts: DataFrame, n: int = 2) -> DataFrame:
    """texts: id, words (array). Entropy in bits of the n-grams of each text: a measure of fluency."""
    grams = F.transform(F.sequence(F.lit(0), F.size("words") - n), lambda i: F.array_join(F.slice("words", i + 1, F.lit(n)), " "))
    rows = texts.filter(F.size("words") >= n).select("id", F.explode(grams).alias("g")).groupBy("id", "g").agg(F.count("*").alias("c"))
    p = F.col("c") / F.sum("c").over(Window.partitionBy("id"))
    return rows.withColumn("p", p).groupBy("id").agg((-F.sum(F.col("p") * F.log2("p"))).alias("entropy"))


# ---------------------------------------------------------------- memory similarity


def entity_jaccard(freq: DataFrame, k: int = 50) -> DataFrame:
    """freq: target, generator, entity, n. Jaccard of the k most frequent entities of every pair of generators, by target."""
    at = F.row_number().over(Window.partitionBy("target", "generator").orderBy(F.desc("n"), "entity"))
    top = freq.withColumn("at", at).filter(F.col("at") <= k).select("target", "generator", "entity")
    sizes = top.groupBy("target", "generator").agg(F.count("*").alias("size"))
    shared = top.withColumnRenamed("generator", "a").join(top.withColumnRenamed("generator", "b"), ["target", "entity"]).groupBy("target", "a", "b").agg(F.count("*").alias("both"))
    pairs = sizes.select("target", F.col("generator").alias("a"), F.col("size").alias("na")).join(sizes.select("target", F.col("generator").alias("b"), F.col("size").alias("nb")), "target")
    rows = pairs.join(shared, ["target", "a", "b"], "left").withColumn("both", F.coalesce("both", F.lit(0)))
    return rows.select("target", "a", "b", (F.col("both") / (F.col("na") + F.col("nb") - F.col("both"))).alias("value"))


def freq_cosine(freq: DataFrame) -> DataFrame:
    """Cosine of the frequency vectors on the union of entities, for every pair of generators, by target."""
    norms = freq.groupBy("target", "generator").agg(F.sqrt(F.sum(F.col("n").cast("double") * F.col("n"))).alias("len"))
    a, b = freq.select("target", F.col("generator").alias("a"), "entity", F.col("n").alias("x")), freq.select("target", F.col("generator").alias("b"), "entity", F.col("n").alias("y"))
    dots = a.join(b, ["target", "entity"]).groupBy("target", "a", "b").agg(F.sum(F.col("x").cast("double") * F.col("y")).alias("dot"))
    pairs = norms.select("target", F.col("generator").alias("a"), F.col("len").alias("la")).join(norms.select("target", F.col("generator").alias("b"), F.col("len").alias("lb")), "target")
    return pairs.join(dots, ["target", "a", "b"], "left").select("target", "a", "b", (F.coalesce("dot", F.lit(0.0)) / (F.col("la") * F.col("lb"))).alias("value"))


def similarity_matrix(by_target: DataFrame, generators: list[str]) -> DataFrame:
    """Averages over targets as a matrix."""
    return by_target.groupBy("a").pivot("b", generators).agg(F.round(F.avg("value"), 6))


def attribute_recovery(found: DataFrame, profiles: DataFrame) -> DataFrame:
    """found, profiles: target, attribute, value. By target and attribute of the profile: facts, covered, F1 of the value sets."""
    t, f = profiles.distinct(), found.distinct()
    hit = t.join(f, ["target", "attribute", "value"]).groupBy("target", "attribute").agg(F.count("*").alias("hit"))
    nt, nf = t.groupBy("target", "attribute").agg(F.count("*").alias("facts")), f.groupBy("target", "attribute").agg(F.count("*").alias("named"))
    rows = nt.join(nf, ["target", "attribute"], "left").join(hit, ["target", "attribute"], "left").na.fill(0, ["named", "hit"])
    return rows.select("target", "attribute", "facts", (F.col("named") > 0).alias("covered"), F.round(2 * F.col("hit") / (F.col("facts") + F.col("named")), 6).alias("f1"))


def forget_coverage(samples: DataFrame, nodes: DataFrame, unit: str = "nodes") -> DataFrame:
    """samples: target, obj, cue2. Share of the graph's nodes (or of their strength) but the target that the forget set names."""
    named = samples.select("target", F.explode(F.array("obj", "cue2")).alias("entity")).filter("entity is not null").distinct().withColumn("in_set", F.lit(1.0))
    mass = F.lit(1.0) if unit == "nodes" else F.col("strength")
    rows = nodes.filter("hop > 0").join(named, ["target", "entity"], "left")
    return rows.groupBy("target").agg((F.sum(F.coalesce("in_set", F.lit(0.0)) * mass) / F.sum(mass)).alias("coverage"))


def graph_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """a, b: edges (target, src, dst, w) of two models. By target: Jaccard of the nodes reached, nodes of one only, L1 of weights."""
    x, y = (d.select("target", F.col("dst").alias("entity")).distinct().withColumn(m, F.lit(1)) for d, m in ((a, "in_a"), (b, "in_b")))
    nodes = x.join(y, ["target", "entity"], "full_outer").na.fill(0, ["in_a", "in_b"])
    n = nodes.groupBy("target").agg((F.sum(F.col("in_a") * F.col("in_b")) / F.count("*")).alias("jaccard"), F.sum(F.col("in_a") * (1 - F.col("in_b"))).alias("only_a"), F.sum(F.col("in_b") * (1 - F.col("in_a"))).alias("only_b"))
    e = a.select("target", "src", "dst", F.col("w").alias("wa")).join(b.select("target", "src", "dst", F.col("w").alias("wb")), ["target", "src", "dst"], "full_outer").na.fill(0.0, ["wa", "wb"])
    return n.join(e.groupBy("target").agg(F.sum(F.abs(F.col("wa") - F.col("wb"))).alias("weight_l1")), "target")


def salience_corr(visits: DataFrame, nodes: DataFrame) -> DataFrame:
    """Rank correlation of visits and strength of the nodes but the target."""
    rows = nodes.filter("hop > 0").join(visits, ["target", "entity"], "left").na.fill(0.0, ["visits"])
    w = Window.partitionBy("target")
    mid = lambda c: F.rank().over(w.orderBy(F.round(c, 9))) + (F.count("*").over(Window.partitionBy("target", F.round(c, 9))) - 1) / 2
    return rows.select("target", mid("visits").alias("x"), mid("strength").alias("y")).groupBy("target").agg(F.corr("x", "y").alias("rank_corr"))


# ---------------------------------------------------------------- reports


def shared_target_average(scores: DataFrame, targets: DataFrame) -> DataFrame:
    """scores: generator, strategy, target, metric, value; means over the targets that all sides share."""
    return scores.join(targets.select("target").distinct(), "target", "left_semi").groupBy("generator", "strategy", "metric").agg(F.avg("value").alias("value"))


def rank_marks(scores: DataFrame, lower_better: list[str]) -> DataFrame:
    """scores: strategy, generator, metric, value. Mark 1 for the best and 2 for the second best generator of each strategy and metric."""
    key = F.when(F.col("metric").isin(lower_better), F.col("value")).otherwise(-F.col("value"))
    at = F.dense_rank().over(Window.partitionBy("strategy", "metric").orderBy(F.round(key, 6)))
    return scores.select("strategy", "generator", "metric", "value", F.when(at <= 2, at).alias("mark"))


def supervision_gap(scores: DataFrame, external: list[str], ours: str = "graph_recall") -> DataFrame:
    """By strategy and metric: our value less the least of the externally supervised generators."""
    own = F.max(F.when(F.col("generator") == ours, F.col("value")))
    return scores.groupBy("strategy", "metric").agg((own - F.min(F.when(F.col("generator").isin(external), F.col("value")))).alias("gap"))


def selfcheck_rate(candidates: DataFrame) -> DataFrame:
    """candidates: target, kept. Pairs asked, kept, and their share."""
    return candidates.groupBy("target").agg(F.count("*").alias("asked"), F.sum(F.col("kept").cast("long")).alias("kept"), F.avg(F.col("kept").cast("double")).alias("rate"))
