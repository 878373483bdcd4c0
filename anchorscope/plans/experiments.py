"""The experiments, re-expressed on the given tables: generators by strategies, ablations, sweeps, planted truth.

A grid is one job: model_id = target|generator|strategy is a column, and all models are erased and scored together.
Parts and customers with facts of the star join stand for the well-known entities and for the invented ones.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import metrics
from ..config import RecallConfig
from ..functions import r6, u01
from ..functions.session import cut
from ..operators import baselines, erasure, recall, supervision, walks
from ..operators.erasure import probabilities
from ..sources import carriers, table
from ..sources.responder import PoolResponder
from . import query
from .method import indexed, star

STAR = RecallConfig(n=20, tau=0.3, k=2, budget=40, r=50)
PROBES = 8
GENERATORS = ("expert_probe", "paragraph_qa", "direct_qa", "graph_recall")


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def pairs_of(targets: DataFrame, pool: DataFrame, cfg: RecallConfig, which: tuple[str, ...], coverage: float | None = None) -> tuple[DataFrame, DataFrame, recall.RecallGraph]:
    """(forget pairs (generator, target, cue, ans, n), neighbour pairs (target, cue, ans, n), graph)."""
    ours, near, graph = baselines.graph_recall_pairs(targets, pool, cfg, coverage)
    about = lambda df, name, n: df.select(F.lit(name).alias("generator"), "target", F.col("entity").alias("cue"), F.col("target").alias("ans"), n.cast("long").alias("n"))
    truth = baselines.profile_truth(targets, pool)
    made = {"graph_recall": ours.select(F.lit("graph_recall").alias("generator"), "target", "cue", "ans", "n")}
    if "direct_qa" in which:
        made["direct_qa"] = about(baselines.direct_qa(targets, pool, n=cfg.n).filter("kept"), "direct_qa", F.col("agreed"))
    if "profile_truth" in which:
        made["profile_truth"] = about(truth, "profile_truth", F.col("n"))
    if "expert_probe" in which:  # all external records, agreed by a second responder
        second = baselines.hop_one(targets, pool, cfg.n, 43).select("target", "entity")
        made["expert_probe"] = about(truth.join(second, ["target", "entity"], "left_semi"), "expert_probe", F.col("n"))
    if "paragraph_qa" in which:  # all external records, unchecked, near copies once
        made["paragraph_qa"] = about(baselines.record_paragraphs(targets, pool), "paragraph_qa", F.col("n"))
    return cut(union([made[g] for g in which])), cut(near), graph


def answers_of(*pairs: DataFrame) -> DataFrame:
    """model_id (the target), cue, ans of pairs, for the support of the table."""
    return union([p.select(F.col("target").alias("model_id"), "cue", "ans") for p in pairs])


@dataclass
class Grid:
    """Erased models of a grid: params (model_id = target|generator|strategy; of the cues that are measured: those of probes and `more`), grid (generator, strategy; - and before is the untouched one), base (the table by target)."""

    params: DataFrame
    grid: DataFrame
    base: DataFrame
    asked: DataFrame
    best: DataFrame

    def name(self, target) -> Column:
        return F.concat_ws("|", target, "generator", "strategy")


def by_model(df: DataFrame) -> DataFrame:
    """generator and strategy in place of model_id."""
    return df.withColumn("generator", F.element_at(F.split("model_id", "\\|"), -2)).withColumn("strategy", F.element_at(F.split("model_id", "\\|"), -1))


def erased(targets: DataFrame, pool: DataFrame, forget: DataFrame, near: DataFrame, strategies: tuple[str, ...], *, epochs: int = 5, lr: float = 0.2, budget: int = 60, more: DataFrame | None = None, without: bool = False) -> Grid:
    """All models of the grid, erased in one job. more: target, cue that have to be in the tables too.

    Each generator has the same number of steps for a target (`budget`), shared out by multiplicity, so that what counts is where they go.
    """
    spark = targets.sparkSession
    near_cues = supervision.cooccur(pool, targets.select(F.col("target").alias("cue"))).select(F.col("cue").alias("target"), F.col("ans").alias("cue"), "c")
    asked = cut(metrics.forget_probes(near_cues, PROBES))
    cues = [asked.select("target", "cue"), asked.filter("cue2 is not null").select("target", F.col("cue2").alias("cue")), forget.select("target", "cue"), near.select("target", "cue")]
    cues = union([*cues, *([more.select("target", "cue")] if more is not None else [])]).distinct().filter("cue <> target")
    base = cut(erasure.fit_table(pool, cues.withColumn("model_id", F.col("target")), support=40, without=without, named=answers_of(forget, near)))
    best = base.filter((F.col("ans") != F.col("model_id")) & (F.col("ans") != erasure.OTHER)).groupBy("model_id", "cue").agg(F.max_by("ans", F.struct("logit", "ans")).alias("best")).select(F.col("model_id").alias("target"), "cue", "best")
    grid = forget.select("generator").distinct().crossJoin(spark.createDataFrame([(s,) for s in strategies], "strategy string"))
    grid = grid.unionByName(spark.createDataFrame([("-", "before")], "generator string, strategy string"))
    name = lambda t: F.concat_ws("|", t, "generator", "strategy")
    params = base.crossJoin(F.broadcast(grid)).withColumn("model_id", name(F.col("model_id"))).select("model_id", "cue", "ans", "logit", "ref_logit")
    total = forget.groupBy("generator", "target").agg(F.sum("n").alias("all"))
    f = forget.join(total, ["generator", "target"]).withColumn("n", F.col("n") * budget / F.col("all")).join(F.broadcast(grid), "generator")
    f = f.select(name(F.col("target")).alias("model_id"), "cue", "ans", "n")
    own = ["generator"] if "generator" in near.columns else []  # neighbours of each generator, or the same for all
    near_total = near.groupBy("target", *own).agg(F.sum("n").alias("all"))
    g = near.join(near_total, ["target", *own]).withColumn("n", F.col("n") * budget / F.col("all"))
    g = (g.join(F.broadcast(grid), "generator") if own else g.crossJoin(F.broadcast(grid))).select(name(F.col("target")).alias("model_id"), "cue", "ans", "n")
    measured = [asked.select("target", "cue"), asked.filter("cue2 is not null").select("target", F.col("cue2").alias("cue")), *([more.select("target", "cue")] if more is not None else [])]
    measured = union(measured).distinct().crossJoin(F.broadcast(grid)).select(name(F.col("target")).alias("model_id"), "cue")
    return Grid(cut(erasure.erase(params, f, g, lr=lr, epochs=epochs, wanted=measured)), grid, base, asked, cut(best))


def probe_means(done: Grid) -> DataFrame:
    """generator, strategy, split, kind, value: answers to the probes, means over the targets that all generators share."""
    ask = lambda df, split: df.select("target", F.concat_ws(":", F.lit(split), "kind").alias("kind"), "cue", "cue2", "ans")
    probes = ask(done.asked.withColumn("ans", F.col("target")), "forget").unionByName(ask(done.asked.filter("kind <> 'aa'").join(done.best, ["target", "cue"]).withColumn("ans", F.col("best")), "neighbor"))
    scored = metrics.probe_scores(done.params, probes, target_of=F.substring_index("model_id", "|", 1))
    kinds = by_model(scored.groupBy("model_id", "target", "kind").agg(F.avg("value").alias("value"))).withColumnRenamed("kind", "metric")
    means = metrics.shared_target_average(kinds, done.base.select(F.col("model_id").alias("target")).distinct())
    means = means.select("generator", "strategy", F.substring_index("metric", ":", 1).alias("split"), F.substring_index("metric", ":", -1).alias("kind"), "value")
    return means.unionByName(means.groupBy("generator", "strategy", "split").agg(F.avg("value").alias("value")).withColumn("kind", F.lit("all")))


def run_grid(targets: DataFrame, pool: DataFrame, forget: DataFrame, near: DataFrame, strategies: tuple[str, ...], **options) -> DataFrame:
    """generator, strategy, split, kind, value of the erased models and the untouched one."""
    return probe_means(erased(targets, pool, forget, near, strategies, **options)).withColumn("value", r6("value"))


def member_losses(done: Grid, pool: DataFrame, targets: DataFrame, free: DataFrame) -> DataFrame:
    """Membership: mean loss of facts of the target (forget; higher is better) and of unrelated facts (retain; lower is better)."""
    known = done.asked.filter("kind <> 'qa'").select("target", F.lit("forget").alias("split"), "cue", F.col("target").alias("ans"))
    other = free.join(done.best, ["target", "cue"]).select("target", F.lit("retain").alias("split"), "cue", F.col("best").alias("ans"))
    samples = known.unionByName(other).crossJoin(F.broadcast(done.grid)).select(done.name(F.col("target")).alias("model_id"), F.concat_ws("|", "target", "cue").alias("sample_id"), "split", "cue", "ans")
    loss = metrics.membership_loss(erasure.token_scores(done.params, samples))
    return by_model(loss).groupBy("generator", "strategy", "split").agg(F.avg("loss").alias("value")).withColumn("kind", F.lit("membership_loss"))


def utilities(done: Grid, free: DataFrame) -> DataFrame:
    """Five stand-ins for general abilities, all on cues that have nothing to do with the targets: knowledge (the best answer stays the best), reasoning (that of two cues
    together does), truthfulness (mass on answers met before), factuality (probability of the best answer), fluency (bits of the answers' distribution)."""
    p = probabilities(done.params).withColumn("target", F.substring_index("model_id", "|", 1)).join(free.select("target", "cue"), ["target", "cue"])
    p = cut(p.join(done.best, ["target", "cue"]).select("model_id", "cue", "ans", "p", "p_ref", "best"))
    top = p.groupBy("model_id", "cue").agg(F.max_by("ans", F.struct("p", "ans")).alias("now"), F.max_by("ans", F.struct("p_ref", "ans")).alias("then"), F.sum(F.when(F.col("ans") != erasure.OTHER, F.col("p"))).alias("met"), F.sum(F.when(F.col("ans") == F.col("best"), F.col("p"))).alias("right"), (-F.sum(F.col("p") * F.log2("p"))).alias("bits"))
    means = by_model(top).groupBy("generator", "strategy").agg(F.avg((F.col("now") == F.col("then")).cast("double")).alias("knowledge"), F.avg("met").alias("truthfulness"), F.avg("right").alias("factuality"), F.avg("bits").alias("fluency"))
    at = Window.partitionBy("model_id").orderBy("cue")
    order = p.select("model_id", "cue").distinct().withColumn("next", F.lead("cue").over(at)).filter("next is not null")
    two = order.join(p, ["model_id", "cue"]).join(p.select("model_id", F.col("cue").alias("next"), "ans", F.col("p").alias("q"), F.col("p_ref").alias("q_ref")), ["model_id", "next", "ans"])
    two = two.groupBy("model_id", "cue").agg(F.max_by("ans", F.struct(F.col("p") * F.col("q"), "ans")).alias("now"), F.max_by("ans", F.struct(F.col("p_ref") * F.col("q_ref"), "ans")).alias("then"))
    means = means.join(by_model(two).groupBy("generator", "strategy").agg(F.avg((F.col("now") == F.col("then")).cast("double")).alias("reasoning")), ["generator", "strategy"], "left")
    return means.unpivot(["generator", "strategy"], ["knowledge", "reasoning", "truthfulness", "factuality", "fluency"], "kind", "value").withColumn("split", F.lit("utility"))


def profile_measures(done: Grid, retrained: DataFrame, splits: DataFrame) -> DataFrame:
    """The measures of the second benchmark. splits: target, split (retain, real_people, world_facts), cue. retrained: the table of the same cues without the target's records.

    prob and rouge (words of the best answer) of the target's facts, truth_ratio against all other answers of the cue, forget_quality (p of a Kolmogorov-Smirnov test of truth
    ratios against the retrained table), and the probability of the right answer in each split; utility is the harmonic mean of the splits.
    """
    p = probabilities(done.params).withColumn("target", F.substring_index("model_id", "|", 1)).select("model_id", "target", "cue", "ans", "p")
    facts = cut(done.asked.filter("kind <> 'qa'").select("target", "cue").distinct())
    rows = cut(p.join(facts, ["target", "cue"]))
    prob = rows.filter("ans = target").groupBy("model_id").agg(F.avg("p").alias("value")).withColumn("kind", F.lit("prob"))
    best = rows.groupBy("model_id", "target", "cue").agg(F.max_by("ans", F.struct("p", "ans")).alias("best"))
    said = lambda c: F.regexp_replace(c, "[:#_ ]+", " ")
    rouge = metrics.rouge1_recall(best.select(F.struct("model_id", "cue").alias("id"), said("target").alias("reference"), said("best").alias("output")))
    rouge = rouge.groupBy(F.col("id.model_id").alias("model_id")).agg(F.avg("recall").alias("value")).withColumn("kind", F.lit("rouge"))
    ratios = lambda r: metrics.truth_ratio(r.filter(F.col("ans") != erasure.OTHER).select("model_id", F.concat_ws("|", "target", "cue").alias("sample_id"), (F.col("ans") == F.col("target")).alias("is_right"), F.col("p").alias("prob"))).filter("ratio is not null")
    own = cut(ratios(rows))
    truth = own.groupBy("model_id").agg(F.avg(F.greatest(F.lit(0.0), 1 - 1 / F.col("ratio"))).alias("value")).withColumn("kind", F.lit("truth_ratio"))
    again = ratios(probabilities(retrained).withColumn("target", F.col("model_id")).select("model_id", "target", "cue", "ans", "p").join(facts, ["target", "cue"])).select(F.col("model_id").alias("target"), "ratio")
    models = own.select("model_id").distinct().withColumn("target", F.substring_index("model_id", "|", 1))
    both = own.select("model_id", F.lit("a").alias("side"), F.col("ratio").alias("value")).unionByName(models.join(again, "target").select("model_id", F.lit("b").alias("side"), F.col("ratio").alias("value")))
    quality = metrics.ks_quality(both).filter("not isnan(p)").select("model_id", F.col("p").alias("value"), F.lit("forget_quality").alias("kind"))
    right = p.join(splits, ["target", "cue"]).join(done.best, ["target", "cue"]).filter("ans = best").groupBy("model_id", F.col("split").alias("kind")).agg(F.avg("p").alias("value"))
    utility = metrics.model_utility(right.withColumnRenamed("kind", "split")).select("model_id", F.lit("utility").alias("kind"), F.col("utility").alias("value"))
    every = union([x.select("model_id", "kind", "value") for x in (prob, rouge, truth, quality, right, utility)])
    return by_model(every).groupBy("generator", "strategy", "kind").agg(F.avg("value").alias("value")).withColumn("split", F.lit("profiles"))


def marked(rows: DataFrame) -> DataFrame:
    """Adds mark (1 and 2 for the best generators of each strategy and kind) and gap (on the row of ours: its value less the least of the externally supervised ones)."""
    lower = ["forget:fb", "forget:qa", "forget:aa", "forget:all", "retain:membership_loss", "profiles:prob", "profiles:rouge"]
    scores = cut(rows.select("generator", "strategy", F.concat_ws(":", "split", "kind").alias("metric"), "value"))
    marks = metrics.rank_marks(scores, lower)
    gaps = metrics.supervision_gap(scores, ["expert_probe", "paragraph_qa", "profile_truth"])
    out = marks.join(gaps, ["strategy", "metric"], "left")
    ours = F.when(F.col("generator") == "graph_recall", r6("gap"))
    return out.select("generator", "strategy", F.substring_index("metric", ":", 1).alias("split"), F.substring_index("metric", ":", -1).alias("kind"), r6("value").alias("value"), F.when(F.col("strategy") != "before", F.col("mark")).alias("mark"), ours.alias("gap"))


def parts(spark: SparkSession, d: str, n: int) -> tuple[DataFrame, DataFrame]:
    pool, targets = star(spark, d, n)
    return pool, cut(targets)


@query()
def exp_main(spark, d):
    """Four strategies by four generators and the untouched model, eight targets; own forget sets cover 90 % of their graphs. Probes, membership, five utilities, marks and gaps."""
    pool, targets = parts(spark, d, 8)
    return main_table(targets, pool, STAR, erasure.STRATEGIES)


def main_table(targets: DataFrame, pool: DataFrame, cfg: RecallConfig, strategies: tuple[str, ...]) -> DataFrame:
    forget, near, graph = pairs_of(targets, pool, cfg, GENERATORS, 0.9)
    free = cut(baselines.neighbor_general(pool, graph.nodes, 20).select("target", F.col("entity").alias("cue")))
    done = erased(targets, pool, forget, near, strategies, more=free)
    return marked(union([x.select("generator", "strategy", "split", "kind", "value") for x in (probe_means(done), member_losses(done, pool, targets, free), utilities(done, free))]))


@query()
def exp_main_words(spark, d):
    """The same on texts: frequent words of documents as targets."""
    pool = indexed(spark, d, "doc_words", carriers.doc_words)
    targets = cut(carriers.frequent(pool, 2))
    return main_table(targets, pool, STAR.but(tau=0.15), ("ga",))


@query()
def exp_small_memory(spark, d):
    """Smaller memories erased: a quarter of the pool's records plays the smaller model."""
    pool, targets = parts(spark, d, 4)
    return main_table(targets, carriers.cut_pool(carriers.some_records(pool, u01(11, "record_id") < 0.25)), STAR, ("ga", "ga_gd"))


@query()
def similarity_matrices(spark, d):
    """Every pair of generators: cosine of frequencies and Jaccard of the 50 most frequent entities that they ask by, means over targets."""
    pool, targets = parts(spark, d, 8)
    asked = cut(pairs_of(targets, pool, STAR, GENERATORS, 0.9)[0].select("target", "generator", F.col("cue").alias("entity"), "n"))
    mean = lambda df, name: df.groupBy("a", "b").agg(r6(F.avg("value")).alias(name))
    return mean(metrics.freq_cosine(asked), "cosine").join(mean(metrics.entity_jaccard(asked), "jaccard"), ["a", "b"])


@query()
def attribute_tables(spark, d):
    """Attributes of customers' true profiles that direct questions and graph recall name: facts, covered, F1 by generator and attribute, means over targets."""
    pool = indexed(spark, d, "customer_facts", carriers.customer_facts)
    targets = cut(carriers.frequent(pool, 8, "cust:%"))
    asked = pairs_of(targets, pool, STAR.but(n=5, tau=0.4, k=2), ("direct_qa", "graph_recall"))[0]
    truth = cut(baselines.profile_truth(targets, pool).select("target", F.substring_index("entity", ":", 1).alias("attribute"), F.col("entity").alias("value")))
    named = asked.select("generator", "target", F.substring_index("cue", ":", 1).alias("attribute"), F.col("cue").alias("value"))
    rows = union([metrics.attribute_recovery(named.filter(F.col("generator") == g).drop("generator"), truth).withColumn("generator", F.lit(g)) for g in ("direct_qa", "graph_recall")])
    return rows.groupBy("generator", "attribute").agg(F.sum("facts").alias("facts"), r6(F.avg(F.col("covered").cast("double"))).alias("covered"), r6(F.avg("f1")).alias("f1"))


@query()
def similarity_generators(spark, d):
    """Cosine and Jaccard of what the generators of `exp_main` ask by, against paragraph questions: means over targets."""
    return similarity_matrices(spark, d).filter("b = 'paragraph_qa'").select("a", "cosine", "jaccard")


@query()
def exp_profiles(spark, d):
    """Invented entities: exact profiles, direct questions and graph recall at few responses, by the measures of the second benchmark."""
    pool = indexed(spark, d, "customer_facts", carriers.customer_facts)
    targets = cut(carriers.frequent(pool, 4, "cust:%"))
    forget, near, graph = pairs_of(targets, pool, STAR.but(n=5, tau=0.4, k=2), ("profile_truth", "direct_qa", "graph_recall"))
    free = pool.select("entity").distinct().join(graph.nodes.select("entity").distinct(), "entity", "left_anti")
    splits = [("retain", "cust:%"), ("real_people", "supp:%"), ("world_facts", "%nation:%")]
    few = union([free.filter(F.col("entity").like(like)).orderBy(u01(42, "entity"), "entity").limit(15).select(F.lit(s).alias("split"), F.col("entity").alias("cue")) for s, like in splits])
    few = cut(targets.crossJoin(F.broadcast(few)))  # 45 cues by target
    done = erased(targets, pool, forget, near, erasure.STRATEGIES, more=few)
    again = erasure.fit_table(pool, done.asked.filter("kind <> 'qa'").select("target", "cue").distinct().withColumn("model_id", F.col("target")), support=40, without=True)
    return marked(union([x.select("generator", "strategy", "split", "kind", "value") for x in (probe_means(done), profile_measures(done, again, few))]))


@query()
def exp_neighbor_source(spark, d):
    """Own neighbours against general ones, for the strategies that use them."""
    pool, targets = parts(spark, d, 4)
    forget, near, graph = pairs_of(targets, pool, STAR, ("graph_recall",))
    general = baselines.neighbor_general(pool, graph.nodes, 20)
    rows = supervision.cooccur(pool, general.select(F.col("entity").alias("cue")).distinct())
    best = rows.groupBy("cue").agg(F.max_by("ans", F.struct("c", "ans")).alias("ans"))
    other = general.select("target", F.col("entity").alias("cue")).join(best, "cue").filter("ans <> target").select("target", "cue", "ans", F.lit(1).cast("long").alias("n"))
    own = run_grid(targets, pool, forget, near, ("ga_gd", "ga_kl")).withColumn("neighbors", F.lit("own"))
    return own.unionByName(run_grid(targets, pool, forget, cut(other), ("ga_gd", "ga_kl")).withColumn("neighbors", F.lit("general")))


@query()
def exp_coverage(spark, d):
    """Forget sets that stop at lower shares of their graphs: walks are added only until .9, .7, .5, .3 of the nodes are met."""
    pool, targets = parts(spark, d, 4)
    _, near, graph = pairs_of(targets, pool, STAR, ("graph_recall",))
    paths = cut(walks.filter_paths(walks.sample_walks(graph.edges, graph.nodes, STAR.but(r=400)), STAR.eta, STAR.eta_mode))
    steps = paths.select("target", "walk_id", F.explode("nodes").alias("node")).filter("node <> target")
    first = steps.groupBy("target", "node").agg(F.min("walk_id").alias("walk_id"))
    size = graph.nodes.filter("hop > 0").groupBy("target").agg(F.count("*").alias("of"))
    met = first.groupBy("target", "walk_id").agg(F.count("*").alias("new")).withColumn("met", F.sum("new").over(Window.partitionBy("target").orderBy("walk_id")))
    met = cut(met.join(size, "target"))
    cuts = []
    for share in (0.9, 0.7, 0.5, 0.3):  # the first walk that reaches the share; all if none does
        last = met.groupBy("target").agg(F.coalesce(F.min(F.when(F.col("met") >= share * F.col("of"), F.col("walk_id"))), F.max("walk_id")).alias("last"))
        rows = steps.join(last, "target").filter("walk_id <= last").groupBy("target", F.col("node").alias("cue")).agg(F.count("*").alias("n"))
        cuts.append(rows.select(F.lit(f"share_{share}").alias("generator"), "target", "cue", F.col("target").alias("ans"), "n"))
    return run_grid(targets, pool, cut(union(cuts)), near, erasure.STRATEGIES)


@query()
def exp_correct_mix(spark, d):
    """Share of right pairs from 0 to 100 %: the others ask by a keyed entity of the pool that the target was never met with."""
    pool, targets = parts(spark, d, 4)
    forget, near, _ = pairs_of(targets, pool, STAR, ("graph_recall",))
    facts = cut(baselines.profile_truth(targets, pool).select("target", F.col("entity").alias("wrong")))
    # as many as a target has pairs, after its facts: so many of the first entities in keyed order hold enough for every target
    need = max((r["n"] for r in forget.select("target").unionByName(facts.select("target")).groupBy("target").agg(F.count("*").alias("n")).collect()), default=0) + 1
    first = pool.select(F.col("entity").alias("wrong")).distinct().orderBy(u01(6, "wrong"), "wrong").limit(need)
    wrong = targets.crossJoin(F.broadcast(first)).join(facts, ["target", "wrong"], "left_anti").filter("wrong <> target")
    order = lambda c, *seed: F.row_number().over(Window.partitionBy("target").orderBy(u01(*seed, c), c))
    numbered = forget.withColumn("at", order("cue", 5, "target"))
    wrong = cut(wrong.withColumn("at", order("wrong", 6)))
    size = forget.groupBy("target").agg(F.count("*").alias("of"))
    mixes = []
    for k in range(0, 11):
        rows = numbered.join(size, "target").join(wrong, ["target", "at"], "left").withColumn("right", F.col("at") <= F.col("of") * k / 10)
        mixes.append(rows.select(F.lit(f"right_{k * 10:03d}").alias("generator"), "target", F.when(F.col("right"), F.col("cue")).otherwise(F.col("wrong")).alias("cue"), "ans", "n").filter("cue is not null"))
    return run_grid(targets, pool, cut(union(mixes)), near, ("ga",))


def profile(graph: recall.RecallGraph, label: dict) -> DataFrame:
    rows = recall.recall_overhead(graph.log, graph.nodes)
    kept = graph.edges.filter("kept").groupBy("target").agg(F.count("*").alias("kept_edges"))
    rows = rows.join(kept, "target", "left").na.fill(0, ["kept_edges"])
    return rows.select(*[F.lit(v).alias(k) for k, v in label.items()], "target", "iterations", "calls", "nodes", "kept_edges")


@query()
def exp_param_sweep(spark, d):
    """Responses, threshold and hops one by one: what each does to nodes, edges and cost."""
    pool = cut(carriers.basket(spark, d, "p_name"))
    targets = cut(carriers.frequent(pool, 2))
    base = RecallConfig(n=20, tau=0.2, k=2, budget=100)
    grid = [("n", v, base.but(n=v)) for v in (5, 10, 40)] + [("tau", v, base.but(tau=v)) for v in (0.15, 0.2, 0.3)] + [("k", v, base.but(k=v)) for v in (1, 2, 3)]
    return union([profile(recall.expand(targets, PoolResponder(pool, n=c.n), c), {"parameter": p, "value": float(v)}) for p, v, c in grid])


@query()
def exp_walk_sweep(spark, d):
    """Walks, their length, exploration and the quality filter one by one: what each does to paths, to the nodes met, and to forgetting."""
    pool, targets = parts(spark, d, 2)
    graph = recall.expand(targets, PoolResponder(pool, n=STAR.n), STAR)
    near = cut(baselines.neighbor_general(pool, graph.nodes, 1).select("target", F.col("entity").alias("cue"), F.col("entity").alias("ans"), F.lit(1).cast("long").alias("n")).filter("cue <> ans"))
    grid = [("r", v, STAR.but(r=v)) for v in (10, 50, 200)] + [("l", v, STAR.but(l=v)) for v in (2, 4, 8)] + [("alpha", v, STAR.but(alpha=v)) for v in (0.0, 1.0, 2.0)] + [("eta", v, STAR.but(eta=v)) for v in (0.0, 0.25, 0.75)]
    made, counts = [], []
    for name, value, cfg in grid:
        paths = walks.filter_paths(walks.sample_walks(graph.edges, graph.nodes, cfg), cfg.eta, cfg.eta_mode)
        rows = cut(paths.select("target", "walk_id", F.explode("nodes").alias("cue")).filter("cue <> target").groupBy("target", "cue").agg(F.count_distinct("walk_id").alias("n")))
        label = f"{name}={value:g}"
        made.append(rows.select(F.lit(label).alias("generator"), "target", "cue", F.col("target").alias("ans"), "n"))
        counts.append(rows.agg(F.count("*").alias("nodes_met"), F.sum("n").alias("visits")).withColumn("generator", F.lit(label)))
    scores = run_grid(targets, pool, cut(union(made)), near, ("ga",)).filter("split = 'forget' and kind = 'all' and strategy = 'ga'")
    return scores.join(union(counts), "generator").select(F.col("generator").alias("parameter"), "nodes_met", "visits", F.col("value").alias("forget"))


@query()
def exp_overhead(spark, d):
    """Iterations, calls and nodes of dense and sparse carriers."""
    todo = [("star_facts", carriers.star_facts, "part:%", STAR), ("customer_facts", carriers.customer_facts, "cust:%", STAR.but(n=10, tau=0.5)), ("basket_part", lambda s, x: carriers.basket(s, x, "l_partkey"), None, STAR.but(tau=0.1)), ("doc_words", carriers.doc_words, None, STAR.but(tau=0.15))]
    rows = []
    for name, make, like, cfg in todo:
        pool = indexed(spark, d, name, make)
        rows.append(profile(recall.expand(cut(carriers.frequent(pool, 4, like)), PoolResponder(pool, n=cfg.n), cfg), {"carrier": name}))
    return union(rows)


@query()
def exp_model_size(spark, d):
    """Smaller memories: keyed shares of the pool's records."""
    pool, targets = parts(spark, d, 4)
    return union([profile(recall.expand(targets, PoolResponder(carriers.some_records(pool, u01(11, "record_id") < s) if s < 1 else pool, n=20), STAR), {"share": s}) for s in (0.25, 0.5, 1.0)])


@query()
def exp_ablation(spark, d):
    """Without conditioning, with uniform walks, without the quality filter, and with nodes in place of paths."""
    pool, targets = parts(spark, d, 4)
    variants = {"full": STAR, "no_conditioning": STAR.but(conditioning="none"), "uniform_walks": STAR.but(weighting="uniform"), "no_filter": STAR.but(eta=0.0, eta_mode="absolute")}
    made, near, graph = [], [], None
    for name, cfg in variants.items():
        ours, others, g = baselines.graph_recall_pairs(targets, pool, cfg)
        made.append(ours.select(F.lit(name).alias("generator"), "target", "cue", "ans", "n"))
        near.append(others.select(F.lit(name).alias("generator"), "target", "cue", "ans", "n"))
        graph = graph or g
    near.append(near[0].withColumn("generator", F.lit("isolated_nodes")))
    alone = graph.nodes.filter("hop > 0").select(F.lit("isolated_nodes").alias("generator"), "target", F.col("entity").alias("cue"), F.col("target").alias("ans"), F.lit(1).cast("long").alias("n"))
    return run_grid(targets, pool, cut(union([*made, alone])), cut(union(near)), ("ga", "ga_gd"))


@query()
def exp_cross_model(spark, d):
    """Two models with memories from disjoint halves of the sources: how their graphs differ."""
    lines = carriers.doc_words(spark, d).withColumn("doc_id", F.substring_index("record_id", ":", 1).cast("long"))
    half = table(spark, d, "documents").select("doc_id", (F.regexp_extract("source", "([0-9]+)", 1).cast("int") % 2).alias("half"))
    pools = [cut(lines.join(half.filter(F.col("half") == h), "doc_id").select("record_id", "entity")) for h in (0, 1)]
    both = pools[0].select("entity").intersect(pools[1].select("entity"))
    targets = cut(carriers.frequent(pools[0].join(both, "entity", "left_semi").unionByName(pools[1].join(both, "entity", "left_semi")), 4))
    cfg = STAR.but(tau=0.1, k=1)
    a, b = (recall.expand(targets, PoolResponder(p, n=cfg.n), cfg).edges.filter("kept") for p in pools)
    return metrics.graph_diff(a, b).select("target", r6("jaccard").alias("jaccard"), "only_a", "only_b", r6("weight_l1").alias("weight_l1"))


def planted_pool(spark: SparkSession, d: str, targets: int = 6, records: int = 60, noise: int = 200) -> DataFrame:
    """Records of known facts: each target has three facts met in 90, 50 and 20 % of its records, and noise words."""
    keys = table(spark, d, "part").select("p_partkey").orderBy("p_partkey").limit(targets)
    rows = keys.select(F.concat(F.lit("T"), F.col("p_partkey").cast("string")).alias("t"), F.explode(F.sequence(F.lit(1), F.lit(records))).alias("i"))
    rows = rows.withColumn("record_id", F.concat_ws(":", "t", "i"))
    facts = F.array(*[F.when(u01(F.lit(f"f{k}"), "t", "i") < p, F.concat_ws("-", "t", F.lit(f"fact{p}"))) for k, p in enumerate((0.9, 0.5, 0.2))])
    dust = F.array(*[F.concat(F.lit("noise"), F.floor(u01(F.lit(f"n{k}"), "t", "i") * noise).cast("string")) for k in range(4)])
    return rows.select("record_id", F.explode(F.concat(F.array("t"), facts, dust)).alias("entity")).filter("entity is not null").distinct()


@query()
def planted_recovery(spark, d):
    """Recall of the facts planted at each rate and precision of the kept nodes, by threshold."""
    pool = cut(planted_pool(spark, d))
    targets = cut(pool.filter("entity not like '%-%' and entity like 'T%'").select(F.col("entity").alias("target")).distinct())
    rows = []
    for tau in (0.1, 0.3, 0.5, 0.7):
        cfg = RecallConfig(n=40, tau=tau, k=1, budget=None)
        nodes = recall.expand(targets, PoolResponder(pool, n=40), cfg).nodes.filter("hop = 1")
        fact = F.col("entity").contains("-fact")
        hit = lambda p: F.sum(F.col("entity").endswith(f"-fact{p}").cast("int")) / F.lit(6.0)
        rows.append(nodes.agg(hit(0.9).alias("recall_90"), hit(0.5).alias("recall_50"), hit(0.2).alias("recall_20"), F.avg(fact.cast("double")).alias("precision")).select(F.lit(tau).alias("tau"), *[r6(F.coalesce(c, F.lit(0.0))).alias(c) for c in ("recall_90", "recall_50", "recall_20", "precision")]))
    return union(rows)


@query()
def utility_scores(spark, d):
    """Unrelated cues before and after erasure: accuracy of the most likely answer, by strategy."""
    pool, targets = parts(spark, d, 2)
    forget, near, graph = pairs_of(targets, pool, STAR.but(k=1), ("graph_recall",))
    free = cut(baselines.neighbor_general(pool, graph.nodes, 10).select("target", F.col("entity").alias("cue")))
    grid = spark.createDataFrame([("before",), *[(s,) for s in erasure.STRATEGIES]], "strategy string")
    base = erasure.fit_table(pool, union([x.select("target", "cue") for x in (free, forget, near)]).distinct().withColumn("model_id", F.col("target")), support=40, named=answers_of(forget, near))
    name = F.concat_ws("|", F.col("model_id"), F.col("strategy"))
    of = lambda df: df.withColumn("model_id", F.col("target")).crossJoin(grid).select(name.alias("model_id"), "cue", "ans", "n")
    params = cut(base.crossJoin(grid).select(name.alias("model_id"), "cue", "ans", "logit", "ref_logit"))
    done = erasure.erase(params, of(forget), of(near))
    top = lambda df, c: df.groupBy("model_id", "cue").agg(F.max_by("ans", F.struct(c, "ans")).alias(c))
    both = top(done, "logit").join(top(done, "ref_logit"), ["model_id", "cue"]).join(free.select("cue").distinct(), "cue", "left_semi")
    return both.groupBy(F.substring_index("model_id", "|", -1).alias("strategy")).agg(r6(F.avg((F.col("logit") == F.col("ref_logit")).cast("double"))).alias("unrelated_accuracy"))


@query()
def walks_adaptive(spark, d):
    """The full method with the coverage rule: walks double until the forget sets cover 90 % of their graphs."""
    from ..api import graph_recall

    pool, targets = parts(spark, d, 2)
    return graph_recall(targets, pool, STAR.but(coverage_target=0.9, r_max=400)).coverage.select("target", r6("coverage").alias("coverage"))


