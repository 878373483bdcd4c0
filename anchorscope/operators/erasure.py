"""The recall table model p(answer | cue) and the four erasure strategies as exact gradient steps on it.

Parameters: (model_id, cue, ans, logit, ref_logit), a softmax over the answers of a cue. A cue's row is bounded by its
support (the most frequent answers, the target, those that pairs name, and one answer for all others), so a task holds single rows of cues.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.session import cut, small
from .supervision import best_answers, met_with

STRATEGIES = ("ga", "bounded_ga", "ga_gd", "ga_kl")
OTHER = "__other__"
PARAMS = "model_id string, cue string, ans string, logit double, ref_logit double"


def fit_table(mentions: DataFrame, cues: DataFrame, *, lam: float = 0.5, support: int = 200, without: bool = False, named: DataFrame | None = None) -> DataFrame:
    """cues: model_id, target, cue. Logits ln(c + lam) of co-mention counts over the whole pool.

    named: model_id, cue, ans that stay answers of their own whatever their rank, as the target does: those that erasure pairs name.

    without: refit with all records that mention the target left out (the ideal that erasure is compared with).
    """
    less = None
    cues = cut(cues)
    if without:  # counts in the records of the target, to be taken off
        aim = cut(met_with(mentions, cues.select(F.col("target").alias("cue")).distinct()).withColumnRenamed("cue", "target"))
        of_cue = cues.select("target", "cue").distinct().join(aim.withColumnRenamed("entity", "cue"), ["target", "cue"])
        less = cut(of_cue.join(aim.withColumnRenamed("entity", "ans"), ["target", "record_id"]).filter("ans <> cue").groupBy("target", "cue", "ans").agg(F.count("*").alias("c")))
    if named is not None:
        named = cut(named.select("model_id", "cue", "ans").distinct())
    also = cues.select(F.col("target").alias("ans")) if named is None else named.select("ans")
    every = cut(best_answers(mentions, cues.select("target", "cue"), support, also, less))
    counts = every.filter("ans is not null").join(cues, ["target", "cue"]).select("model_id", "target", "cue", "ans", "c")
    at = F.row_number().over(Window.partitionBy("model_id", "target", "cue").orderBy((F.col("ans") == F.col("target")).desc(), F.desc("c"), "ans"))
    ranked = counts.withColumn("at", at)
    stays = F.col("at") <= support
    if named is not None:
        ranked = ranked.join(named.withColumn("named", F.lit(True)), ["model_id", "cue", "ans"], "left")
        stays = stays | F.col("named").isNotNull()
    table = cut(ranked.filter(stays).select("model_id", "target", "cue", "ans", "c"))
    total = every.filter("ans is null").join(cues, ["target", "cue"]).join(table.groupBy("model_id", "target", "cue").agg(F.sum("c").alias("kept")), ["model_id", "target", "cue"], "left")
    table = table.unionByName(total.select("model_id", "target", "cue", F.lit(OTHER).alias("ans"), (F.col("c") - F.coalesce("kept", F.lit(0))).alias("c")))
    always = cues.select("model_id", "target", "cue", F.explode(F.array(F.col("target"), F.lit(OTHER))).alias("ans"), F.lit(0).cast("long").alias("c"))
    if named is not None:  # also answers that the cue was never met with
        always = always.unionByName(cues.join(named, ["model_id", "cue"]).select("model_id", "target", "cue", "ans", F.lit(0).cast("long").alias("c")))
    table = table.unionByName(always.filter("ans <> cue")).groupBy("model_id", "cue", "ans").agg(F.max("c").alias("c"))
    logit = F.log(F.col("c") + lam)
    return table.select("model_id", "cue", "ans", logit.alias("logit"), logit.alias("ref_logit"))


def probabilities(params: DataFrame) -> DataFrame:
    """Adds p and p_ref."""
    w = Window.partitionBy("model_id", "cue")
    soft = lambda c: F.exp(F.col(c) - F.max(c).over(w))
    rows = params.withColumn("_e", soft("logit")).withColumn("_r", soft("ref_logit"))
    return rows.withColumn("p", F.col("_e") / F.sum("_e").over(w)).withColumn("p_ref", F.col("_r") / F.sum("_r").over(w)).drop("_e", "_r")


def one_step(params: DataFrame, forget: DataFrame, neighbor: DataFrame | None, strategy: str, *, lr: float = 0.2, beta: float = 1.0) -> DataFrame:
    """One gradient step by windows: pairs are (model_id, cue, ans, n)."""
    w = Window.partitionBy("model_id", "cue")
    pairs = lambda df, name: df.groupBy("model_id", "cue", "ans").agg(F.sum("n").cast("double").alias(name))
    rows = probabilities(params).join(pairs(forget, "f"), ["model_id", "cue", "ans"], "left").withColumn("f", F.coalesce("f", F.lit(0.0)))
    if neighbor is not None and strategy in ("ga_gd", "ga_kl"):
        rows = rows.join(pairs(neighbor, "g"), ["model_id", "cue", "ans"], "left").withColumn("g", F.coalesce("g", F.lit(0.0)))
    else:
        rows = rows.withColumn("g", F.lit(0.0))
    if strategy == "bounded_ga":
        r = F.pow(F.col("p") / F.col("p_ref"), F.lit(float(beta)))
        rows = rows.withColumn("f", F.col("f") * 2 * r / (1 + r))
    step = -(F.col("f") - F.sum("f").over(w) * F.col("p"))
    if strategy == "ga_gd":
        step = step + (F.col("g") - F.sum("g").over(w) * F.col("p"))
    elif strategy == "ga_kl":
        step = step - F.sum("g").over(w) * (F.col("p") - F.col("p_ref"))
    return rows.select("model_id", "cue", "ans", (F.col("logit") + lr * step).alias("logit"), "ref_logit")


#: Parameters that a task updates at once.
ROWS_AT_ONCE = 20_000
#: Rows of pairs that may be broadcast, so that the models' tables, many times larger, need no shuffle to find what is updated.
PAIRS_HELD = 1_000_000


def update_rows(z: np.ndarray, ref: np.ndarray, f: np.ndarray, g: np.ndarray, strategy: np.ndarray, row: np.ndarray, lr: float, epochs: int, beta: float) -> np.ndarray:
    """All epochs of many rows of cues side by side. strategy: by parameter; row: the number of the cue's row that it is in, ascending."""
    begin = np.flatnonzero(np.r_[True, row[1:] != row[:-1]])
    at = np.cumsum(np.r_[True, row[1:] != row[:-1]]) - 1
    total = lambda x: np.add.reduceat(x, begin)[at]

    def soft(x: np.ndarray) -> np.ndarray:
        e = np.exp(x - np.maximum.reduceat(x, begin)[at])
        return e / total(e)

    bounded, gd, kl = (strategy == s for s in ("bounded_ga", "ga_gd", "ga_kl"))
    f, g = np.where(np.isin(strategy, STRATEGIES), f, 0.0), np.where(gd | kl, g, 0.0)
    p_ref, all_g = soft(ref), total(g)
    for _ in range(epochs):
        p = soft(z)
        r = np.where(bounded, p / p_ref, 1.0) ** beta
        push = f * 2 * r / (1 + r)
        step = -(push - total(push) * p)
        step = step + np.where(gd, g - all_g * p, 0.0) - np.where(kl, all_g * (p - p_ref), 0.0)
        z = z + lr * step
    return z


def erase(params: DataFrame, forget: DataFrame, neighbor: DataFrame | None = None, *, lr: float = 0.2, epochs: int = 5, beta: float = 1.0, wanted: DataFrame | None = None) -> DataFrame:
    """All epochs of all models at once: one shuffle by cue, of the cues that pairs ask by. model_id ends in `|strategy`; cues without pairs stay as they are.

    A grid of generators, strategies and targets is thus one job.

    wanted: model_id, cue (distinct) whose rows come back; all models are erased in whole all the same.
    """
    f, g = forget.withColumn("g", F.lit(0.0)).withColumnRenamed("n", "f"), None if neighbor is None else neighbor.withColumn("f", F.lit(0.0)).withColumnRenamed("n", "g")
    pairs = f.select("model_id", "cue", "ans", "f", "g") if g is None else f.select("model_id", "cue", "ans", "f", "g").unionByName(g.select("model_id", "cue", "ans", "f", "g"))
    pairs = cut(pairs.groupBy("model_id", "cue", "ans").agg(F.sum(F.col("f").cast("double")).alias("f"), F.sum(F.col("g").cast("double")).alias("g")))
    touched = cut(pairs.select("model_id", "cue").distinct())
    rows = params.join(small(touched, PAIRS_HELD), ["model_id", "cue"], "left_semi").join(small(pairs, PAIRS_HELD), ["model_id", "cue", "ans"], "left")
    rows = cut(rows.na.fill(0.0, ["f", "g"]))

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["model_id", "cue", "ans"])
        strategy = frame["model_id"].str.rpartition("|")[2].to_numpy(str)
        row = frame.groupby(["model_id", "cue"], sort=True).ngroup().to_numpy()
        z = update_rows(*(frame[c].to_numpy(float) for c in ("logit", "ref_logit", "f", "g")), strategy, row, lr, epochs, beta)
        return frame.assign(logit=z)[["model_id", "cue", "ans", "logit", "ref_logit"]]

    parts = rows.count() // ROWS_AT_ONCE + 1  # whole rows of cues, many in a call
    moved = cut(rows.groupBy(F.pmod(F.xxhash64("model_id", "cue"), F.lit(parts))).applyInPandas(run, PARAMS))
    if wanted is not None:
        wanted = cut(wanted)
        some = small(cut(wanted.select("cue").distinct()))  # by cue alone first, which reaches the tables below a product of models
        params, moved = (df.join(some, "cue", "left_semi").join(small(wanted), ["model_id", "cue"], "left_semi") for df in (params, moved))
    return params.join(small(touched, PAIRS_HELD), ["model_id", "cue"], "left_anti").select("model_id", "cue", "ans", "logit", "ref_logit").unionByName(moved)


def token_scores(params: DataFrame, samples: DataFrame) -> DataFrame:
    """samples: model_id, sample_id, split, cue, ans -> model_id, sample_id, split, pos, is_answer, lp_before, lp_after: an answer of the table is one token.

    The form in which an external trainer hands over its scores too, so all measures of token scores hold for both.
    """
    p = probabilities(params).select("model_id", "cue", "ans", F.log(F.greatest(F.col("p_ref"), F.lit(1e-300))).alias("lp_before"), F.log(F.greatest(F.col("p"), F.lit(1e-300))).alias("lp_after"))
    return samples.join(p, ["model_id", "cue", "ans"]).select("model_id", "sample_id", "split", F.lit(0).alias("pos"), F.lit(True).alias("is_answer"), "lp_before", "lp_after")


def load_token_scores(spark, path: str, fmt: str = "json") -> DataFrame:
    """Token scores of an external trainer, one row a token: sample_id, split, pos, is_answer, lp_before, lp_after; a missing column raises."""
    return spark.read.schema("sample_id string, split string, pos int, is_answer boolean, lp_before double, lp_after double").format(fmt).load(path)


def alternative_response(samples: DataFrame, kind: str = "refusal") -> DataFrame:
    """The answer replaced, for strategies that train on another response instead of against the right one."""
    text = F.lit("I don't know.") if kind == "refusal" else F.lit("an entity of that kind")
    return samples.withColumn("answer", text)


def objective(token_scores: DataFrame, strategy: str) -> DataFrame:
    """Objective by split from token scores of any model, answer tokens only: reverse on the forget side, plain on the neighbour side."""
    on = F.col("is_answer")
    total = token_scores.groupBy("split").agg(F.sum(F.when(on, F.col("lp_after"))).alias("lp"), F.sum(F.when(on, F.col("lp_after") - F.col("lp_before"))).alias("shift"), F.sum(on.cast("long")).alias("tokens"))
    sign = F.when(F.col("split") == "forget", F.lit(1.0)).when(F.lit(strategy in ("ga_gd",)), F.lit(-1.0)).otherwise(F.lit(0.0))
    value = F.when((F.col("split") != "forget") & F.lit(strategy == "ga_kl"), -F.col("shift")).otherwise(sign * F.col("lp"))
    return total.select("split", "tokens", value.alias("objective"))
