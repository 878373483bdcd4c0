"""Queries of the baselines, the table model with its strategies, and the measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .. import metrics
from ..functions import r6, u01
from ..operators import baselines, erasure, supervision
from ..sources import carriers, table
from . import query, sql
from .method import CFG, NAME_RECALL, STAR_RECALL, _forget_sql, indexed, name_graph, names, star, star_forget, star_graph

# ---------------------------------------------------------------- generators


DIRECT = f"""f0 as (select target, target as anchor from targets), {sql.respond('f0', 'ra', 20)}, {sql.respond('f0', 'rb', 20, seed=43)}, {sql.strengths('ra', 'ca', 20, 1)}, {sql.strengths('rb', 'cb', 20, 1)},
    dq as (select target, dst as entity, 2 as asked, count(*) as agreed, count(*) >= 2 as kept from (select target, dst from ca union all select target, dst from cb) group by target, dst)"""


@query(f"with {sql.base('star_facts', 4, 'part:%')}, {DIRECT} select * from dq")
def gen_direct_qa(spark, d):
    pool, targets = star(spark, d, 4)
    return baselines.direct_qa(targets, pool)


@query(f"with {sql.base('star_facts', 4, 'part:%')}, {DIRECT} select target, count(*) as asked, sum(case when kept then 1 else 0 end) as kept, round(avg(case when kept then 1.0 else 0.0 end), 6) as rate from dq group by target")
def selfcheck_rate(spark, d):
    return metrics.selfcheck_rate(gen_direct_qa(spark, d)).select("target", "asked", "kept", r6("rate").alias("rate"))


TRUTH = "tr as (select t.target, p.entity, count(*) as n from targets t join pool a on a.entity = t.target join pool p on p.record_id = a.record_id where p.entity <> t.target group by t.target, p.entity)"


@query(f"with {sql.base('customer_facts', 4, 'cust:%')}, {TRUTH} select * from tr")
def gen_profile_truth(spark, d):
    pool = indexed(spark, d, "customer_facts", carriers.customer_facts)
    return baselines.profile_truth(carriers.frequent(pool, 4, "cust:%"), pool)


@query(f"""with {sql.base('doc_words', 4)}, f0 as (select target, target as anchor from targets), {sql.respond('f0', 'rb', 20, seed=43)}, {sql.strengths('rb', 'cb', 20, 1)},
    bad as (select distinct doc_id from labels where quality = 0 or toxic = 1)
    select t.target, p.entity, count(*) as n from targets t join pool a on a.entity = t.target join pool p on p.record_id = a.record_id where p.entity <> t.target and not exists (select 1 from bad where bad.doc_id = cast(split_part(a.record_id, ':', 1) as bigint))
    and exists (select 1 from cb where cb.target = t.target and cb.dst = p.entity) group by t.target, p.entity""")  # fmt: skip
def gen_expert_probe(spark, d):
    pool = indexed(spark, d, "doc_words", carriers.doc_words)
    return baselines.expert_probe(carriers.frequent(pool, 4), pool, table(spark, d, "labels"))


TOP = "top as (select cast(json_extract_string(props, '$.k') as bigint) as page_id, count(*) as views from events where event_type = 'view' group by 1 order by views desc, 1 limit 20)"
PARAGRAPHS = """pp as (select page_id, i - 1 as "at", trim(regexp_replace(regexp_replace(ps[i], '<[^>]*>', ' ', 'g'), '[ \\t\\r\\n]+', ' ', 'g')) as paragraph from (select page_id, ps, unnest(range(1, len(ps) + 1)) as i from (select page_id, regexp_extract_all(html, '(?s)<p>(.*?)</p>', 1) as ps from pages)))"""


@query(f"with {TOP} select page_id, views from top")
def topk_pages(spark, d):
    return baselines.topk_pages(table(spark, d, "events"))


@query(f"with {PARAGRAPHS} select * from pp where paragraph <> ''")
def html_paragraphs(spark, d):
    return baselines.html_paragraphs(table(spark, d, "pages"))


@query(f'with {TOP}, {PARAGRAPHS} select page_id, "at", paragraph, views from (select pp.*, views from pp join top using (page_id) where paragraph <> \'\') qualify row_number() over (partition by paragraph order by page_id, "at") = 1')
def gen_paragraph_qa(spark, d):
    return baselines.paragraph_qa(table(spark, d, "pages"), baselines.topk_pages(table(spark, d, "events")))


@query("select vec_id from embeddings e where not exists (select 1 from embeddings p where p.vec_id < e.vec_id and list_cosine_similarity(p.embedding::double[], e.embedding::double[]) >= 0.9)")
def embedding_dedup_any(spark, d):
    return baselines.semantic_dedup_any(table(spark, d, "embeddings"), 0.9)


@query()
def embedding_dedup_greedy(spark, d):
    return baselines.semantic_dedup_greedy(table(spark, d, "embeddings"), 0.9)


@query(f"""with {STAR_RECALL}, x as (select distinct p.entity from pool p where not exists (select 1 from nodes n where n.entity = p.entity))
    select target, entity, "at" from (select target, entity, row_number() over (partition by target order by {sql.draw('42', 'entity')}, entity) as "at" from targets, x) where "at" <= 20""")  # fmt: skip
def neighbor_general(spark, d):
    return baselines.neighbor_general(star(spark, d)[0], star_graph(spark, d).nodes)


# ---------------------------------------------------------------- the table model

SUPPORT = 50
CUES = "cues as (select 'm' as model_id, n.target, n.entity as cue from nodes n where n.hop = 1)"
COUNTS = "co as (select c.model_id, c.target, c.cue, p.entity as ans, count(*) as c from cues c join pool a on a.entity = c.cue join pool p on p.record_id = a.record_id where p.entity <> c.cue group by all)"


def _table(counts: str = "co") -> str:
    return f"""rk as (select *, case when row_number() over (partition by model_id, target, cue order by ans = target desc, c desc, ans) <= {SUPPORT} then ans else '__other__' end as a2 from {counts}),
    pr as materialized (select model_id, cue, ans, ln(max(c) + 0.5) as z, ln(max(c) + 0.5) as z0 from (select model_id, target, cue, a2 as ans, sum(c) as c from rk group by all union all select model_id, target, cue, unnest([target, '__other__']), 0 from cues) where ans <> cue group by model_id, cue, ans)"""


MODEL = f"{NAME_RECALL}, {CUES}, {COUNTS}, {_table()}"


def model(spark, d, without: bool = False) -> tuple[DataFrame, DataFrame]:
    g, (pool, _) = name_graph(spark, d), names(spark, d)
    cues = g.nodes.filter("hop = 1").select(F.lit("m").alias("model_id"), "target", F.col("entity").alias("cue"))
    return erasure.fit_table(pool, cues, support=SUPPORT, without=without), cues


@query(f"with {MODEL} select model_id, cue, ans, round(exp(z) / sum(exp(z)) over (partition by model_id, cue), 6) as p from pr")
def table_probs(spark, d):
    return erasure.probabilities(model(spark, d)[0]).select("model_id", "cue", "ans", r6("p").alias("p"))


@query(f"""with {NAME_RECALL}, {CUES}, cx as (select c.model_id, c.target, c.cue, p.entity as ans, count(*) as c from cues c join pool a on a.entity = c.cue join pool p on p.record_id = a.record_id where p.entity <> c.cue
    and not exists (select 1 from pool t where t.entity = c.target and t.record_id = a.record_id) group by all), {_table('cx')} select model_id, cue, ans, round(exp(z) / sum(exp(z)) over (partition by model_id, cue), 6) as p from pr""")  # fmt: skip
def retrain_reference(spark, d):
    return erasure.probabilities(model(spark, d, True)[0]).select("model_id", "cue", "ans", r6("p").alias("p"))


#: Forget pairs: every cue asks for its target twice; neighbour pairs: for its most frequent other answer once.
FORGET = "fp as (select model_id, cue, target as ans, 2.0 as n from cues)"
NEIGHBOR = "np as (select model_id, cue, ans, 1.0 as n from (select co.*, row_number() over (partition by model_id, target, cue order by c desc, ans) as k from co where ans <> target) where k = 1)"


def model_pairs(spark, d) -> tuple[DataFrame, DataFrame, DataFrame]:
    params, cues = model(spark, d)
    pool = names(spark, d)[0]
    forget = cues.select("model_id", "cue", F.col("target").alias("ans"), F.lit(2).cast("long").alias("n"))
    counts = supervision.cooccur(pool, cues.select("cue").distinct()).join(cues, "cue").filter("ans <> target")
    k = F.row_number().over(Window.partitionBy("model_id", "target", "cue").orderBy(F.desc("c"), "ans"))
    neighbor = counts.withColumn("k", k).filter("k = 1").select("model_id", "cue", "ans", F.lit(1).cast("long").alias("n"))
    return params, forget, neighbor


def _step_sql(strategy: str, steps: int) -> str:
    parts = [f"with {MODEL}, {FORGET}, {NEIGHBOR}, ff as (select model_id, cue, ans, sum(n) as n from fp group by all), nn as (select model_id, cue, ans, sum(n) as n from np group by all), z0_ as (select * from pr)"]
    for i in range(steps):
        push = "coalesce(f.n, 0)"
        damp = "2 * (p / p0) / (1 + p / p0)" if strategy == "bounded_ga" else "1"
        parts.append(f"""q{i} as (select b.*, {push} * {damp} as f, coalesce(g.n, 0) as g from (select *, exp(z) / sum(exp(z)) over (partition by model_id, cue) as p, exp(z0) / sum(exp(z0)) over (partition by model_id, cue) as p0 from z{i}_) b
            left join ff f on f.model_id = b.model_id and f.cue = b.cue and f.ans = b.ans left join nn g on g.model_id = b.model_id and g.cue = b.cue and g.ans = b.ans)""")
        extra = {"ga_gd": " + (g - sum(g) over w * p)", "ga_kl": " - sum(g) over w * (p - p0)"}.get(strategy, "")
        parts.append(f"z{i + 1}_ as materialized (select model_id, cue, ans, z + 0.2 * (-(f - sum(f) over w * p){extra}) as z, z0 from q{i} window w as (partition by model_id, cue))")
    return ", ".join(parts) + f" select model_id, cue, ans, round(z, 6) as logit from z{steps}_"


def _strategy(strategy: str, steps: int, name: str):
    @query(_step_sql(strategy, steps), name=name)
    def run(spark, d):
        params, forget, neighbor = model_pairs(spark, d)
        for _ in range(steps):
            params = erasure.one_step(params, forget, neighbor, strategy)
        return params.select("model_id", "cue", "ans", r6("logit").alias("logit"))


_strategy("ga", 1, "ga_one_step")
_strategy("bounded_ga", 2, "bounded_two_steps")
_strategy("ga_gd", 1, "ga_gd_one_step")
_strategy("ga_kl", 2, "ga_kl_two_steps")


@query()
def erase_epochs(spark, d):
    """All strategies over five epochs on the same table, one job."""
    params, forget, neighbor = model_pairs(spark, d)
    every = lambda df: df.drop("model_id").crossJoin(spark.createDataFrame([(f"m|{s}",) for s in erasure.STRATEGIES], "model_id string"))  # noqa: E731  four rows
    return erasure.erase(every(params).select("model_id", "cue", "ans", "logit", "ref_logit"), every(forget), every(neighbor)).select("model_id", "cue", "ans", r6("logit").alias("logit"))


def _alternative(kind: str, text: str):
    @query(_forget_sql("non_target", "qa") + f" select sample_id, question, '{text}' as answer from q", name=f"{kind}_samples")
    def run(spark, d):
        return erasure.alternative_response(star_forget(spark, d)[0], kind).select("sample_id", "question", "answer")


_alternative("refusal", "I don''t know.")
_alternative("generic", "an entity of that kind")

# ---------------------------------------------------------------- token scores (keyed stand-ins for an external trainer's output)

SCORES = f"""ts as materialized (select cast(conv_id * 100 + turn as varchar) as sample_id, case when role = 'user' then 'forget' else 'retain' end as split, i as pos, i >= 3 as is_answer,
    -5 * {sql.draw("'b'", 'conv_id', 'turn', 'i')} as lp_before, -5 * {sql.draw("'a'", 'conv_id', 'turn', 'i')} as lp_after from conversations, (select unnest(range(8)) as i))"""


def token_scores(spark, d) -> DataFrame:
    rows = table(spark, d, "conversations").select("conv_id", "turn", "role", F.explode(F.sequence(F.lit(0), F.lit(7))).alias("pos"))
    name = (F.col("conv_id") * 100 + F.col("turn")).cast("string")
    split = F.when(F.col("role") == "user", "forget").otherwise("retain")
    return rows.select(name.alias("sample_id"), split.alias("split"), "pos", (F.col("pos") >= 3).alias("is_answer"), (-5 * u01(F.lit("b"), "conv_id", "turn", "pos")).alias("lp_before"), (-5 * u01(F.lit("a"), "conv_id", "turn", "pos")).alias("lp_after"))


@query(f"with {SCORES} select split, round(avg(nll), 6) as loss from (select split, sample_id, avg(-lp_after) as nll from ts group by all) group by split")
def membership_loss(spark, d):
    return metrics.membership_loss(token_scores(spark, d)).select("split", r6("loss").alias("loss"))


@query(f"with {SCORES} select sample_id, round(exp(avg(lp_after)), 6) as prob from ts where is_answer group by sample_id")
def answer_prob(spark, d):
    return metrics.answer_prob(token_scores(spark, d)).select("sample_id", r6("prob").alias("prob"))


def _objective(strategy: str) -> str:
    other = {"ga_gd": "-sum(lp_after)", "ga_kl": "-sum(lp_after - lp_before)"}.get(strategy, "0.0")
    return f"select '{strategy}' as strategy, split, count(*) as tokens, round(case when split = 'forget' then sum(lp_after) else {other} end, 6) + 0.0 as objective from ts where is_answer group by split"


@query(f"with {SCORES} " + " union all ".join(_objective(s) for s in erasure.STRATEGIES))
def objective_values(spark, d):
    rows = None
    for s in erasure.STRATEGIES:
        one = erasure.objective(token_scores(spark, d), s).select(F.lit(s).alias("strategy"), "split", "tokens", (r6("objective") + 0.0).alias("objective"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


RATIOS = f"""an as (select cast(conv_id as varchar) as sample_id, turn = 0 as is_right, 0.05 + {sql.draw("'t'", 'conv_id', 'turn')} as prob, conv_id from conversations where turn < 4), tr_ as (select sample_id, any_value(conv_id) as conv_id, avg(prob) filter (not is_right) / max(prob) filter (is_right) as ratio from an group by sample_id)"""


def ratios(spark, d) -> DataFrame:
    rows = table(spark, d, "conversations").filter("turn < 4").select(F.col("conv_id").cast("string").alias("sample_id"), (F.col("turn") == 0).alias("is_right"), (0.05 + u01(F.lit("t"), "conv_id", "turn")).alias("prob"))
    return metrics.truth_ratio(rows)


@query(f"with {RATIOS} select sample_id, round(ratio, 6) as ratio from tr_")
def truth_ratio(spark, d):
    return ratios(spark, d).select("sample_id", r6("ratio").alias("ratio"))


@query(f"""with {RATIOS}, v as (select case when conv_id % 2 = 0 then 'a' else 'b' end as side, round(ratio, 9) as value from tr_ where ratio is not null), t as (select value, sum((side = 'a')::int) as a, sum((side = 'b')::int) as b from v group by value),
    c as (select sum(a) over (order by value) as a, sum(b) over (order by value) as b from t), n as (select sum((side = 'a')::int) as na, sum((side = 'b')::int) as nb from v) select na, nb, round(max(abs(c.a / na - c.b / nb)), 6) as d from c, n group by na, nb""")  # fmt: skip
def ks_statistic(spark, d):
    side = F.when(F.col("sample_id").cast("long") % 2 == 0, "a").otherwise("b")
    rows = ratios(spark, d).filter("ratio is not null").select(side.alias("side"), F.round("ratio", 9).alias("value"))
    return metrics.ks_statistic(rows).select("na", "nb", r6("d").alias("d"))


PAIR_TEXTS = """select conv_id * 100 + turn as id, trim(regexp_replace(text, '[ \\t\\r\\n]+', ' ', 'g')) as reference, trim(regexp_replace(nxt, '[ \\t\\r\\n]+', ' ', 'g')) as output from (select *, lead(text) over (partition by conv_id order by turn) as nxt from conversations) where nxt is not null"""


def text_pairs(spark, d) -> DataFrame:
    w = Window.partitionBy("conv_id").orderBy("turn")
    fold = lambda c: F.trim(F.regexp_replace(c, "[ \\t\\r\\n]+", " "))
    return table(spark, d, "conversations").withColumn("nxt", F.lead("text").over(w)).filter("nxt is not null").select((F.col("conv_id") * 100 + F.col("turn")).alias("id"), fold("text").alias("reference"), fold("nxt").alias("output"))


@query(f"with p as ({PAIR_TEXTS}), w as (select id, list_distinct(string_split(reference, ' ')) as a, list_distinct(string_split(output, ' ')) as b from p) select id, round(len(list_intersect(a, b)) / len(a), 6) as recall from w")
def rouge1_recall(spark, d):
    return metrics.rouge1_recall(text_pairs(spark, d)).select("id", r6("recall").alias("recall"))


@query()
def rouge_lcs_recall(spark, d):
    return metrics.rouge_lcs_recall(text_pairs(spark, d)).select("id", r6("recall").alias("recall"))


@query(f"""with p as ({PAIR_TEXTS}), w as (select id, string_split(reference, ' ') as a from p), g as (select id, a[i] || ' ' || a[i + 1] as g, count(*) as c from (select id, a, unnest(range(1, len(a))) as i from w where len(a) >= 2) group by all),
    q as (select id, c / sum(c) over (partition by id) as p from g) select id, round(-sum(p * log2(p)), 6) + 0.0 as entropy from q group by id""")  # fmt: skip
def ngram_entropy(spark, d):
    return metrics.ngram_entropy(text_pairs(spark, d).select("id", F.split("reference", " ").alias("words"))).select("id", (r6("entropy") + 0.0).alias("entropy"))


@query(f"with {RATIOS}, s as (select case when conv_id % 2 = 0 then 'a' else 'b' end as model_id, cast(conv_id % 3 as varchar) as split, avg(ratio) as value from tr_ group by all) select model_id, round(count(*) / sum(1 / value), 6) as utility from s group by model_id")
def model_utility(spark, d):
    i = F.col("sample_id").cast("long")
    rows = ratios(spark, d).groupBy(F.when(i % 2 == 0, "a").otherwise("b").alias("model_id"), (i % 3).cast("string").alias("split")).agg(F.avg("ratio").alias("value"))
    return metrics.model_utility(rows).select("model_id", r6("utility").alias("utility"))


# ---------------------------------------------------------------- probes


PROBES = f"""cc as (select t.target, p.entity as cue, count(*) as c from targets t join pool a on a.entity = t.target join pool p on p.record_id = a.record_id where p.entity <> t.target group by all),
    rk2 as (select *, row_number() over (partition by target order by c desc, cue) as k from cc), cues as (select 'm' as model_id, target, cue from rk2 where k <= 6),
    pb as (select target, case when k <= 3 then 'fb' else 'aa' end as kind, cue, cast(null as varchar) as cue2, target as ans from rk2 where k <= 6 union all
        select a.target, 'qa', a.cue, b.cue, a.target from rk2 a join rk2 b on b.target = a.target and b.k = a.k + 3 where a.k <= 3)"""
SCORED = """pp_ as materialized (select *, exp(z) / sum(exp(z)) over (partition by model_id, cue) as p from pr),
    sc as (select b.target, b.kind, x.p as value from pb b join pp_ x on x.cue = b.cue and x.ans = b.ans where b.cue2 is null union all
        select target, kind, coalesce(sum(case when a = want then pq end), 0) / sum(pq) from (select b.target, b.kind, b.cue, b.cue2, b.ans as want, x.ans as a, x.p * y.p as pq from pb b join pp_ x on x.cue = b.cue join pp_ y on y.cue = b.cue2 and y.ans = x.ans where b.cue2 is not null) group by target, kind, cue, cue2, want),
    gk as (select target, kind, avg(value) as value from sc group by all), ga_ as (select * from gk union all select target, 'all', avg(value) from gk group by target) select target, kind, round(value, 6) as value from ga_"""


def probes(spark, d, k: int = 3) -> tuple[DataFrame, DataFrame, DataFrame]:
    pool, targets = names(spark, d)
    near = supervision.cooccur(pool, targets.withColumnRenamed("target", "cue")).select(F.col("cue").alias("target"), F.col("ans").alias("cue"), "c")
    asked = metrics.forget_probes(near, k)
    cues = asked.select(F.lit("m").alias("model_id"), "target", "cue").unionByName(asked.filter("cue2 is not null").select(F.lit("m").alias("model_id"), "target", F.col("cue2").alias("cue"))).distinct()
    return pool, asked, cues


@query(f"with {sql.base('basket_name', 2)}, {PROBES}, {COUNTS}, {_table()}, {SCORED}")
def forget_scores(spark, d):
    pool, asked, cues = probes(spark, d)
    scored = metrics.probe_scores(erasure.fit_table(pool, cues, support=SUPPORT), asked.withColumn("ans", F.col("target")))
    return metrics.grouped_scores(scored).select("target", "kind", r6("value").alias("value"))


@query(f"""with {sql.base('basket_name', 2)}, {PROBES.replace('pb as (', 'pb0 as (')}, {COUNTS}, best as (select target, cue, ans from (select *, row_number() over (partition by target, cue order by c desc, ans) as k from co where ans <> target) where k = 1),
    pb as (select p.target, p.kind, p.cue, p.cue2, b.ans from pb0 p join best b on b.target = p.target and b.cue = p.cue where p.kind <> 'aa'), {_table()}, {SCORED}""")  # fmt: skip
def neighbor_scores(spark, d):
    pool, asked, cues = probes(spark, d)
    counts = supervision.cooccur(pool, cues.select("cue").distinct()).join(cues, "cue").filter("ans <> target")
    best = counts.withColumn("k", F.row_number().over(Window.partitionBy("target", "cue").orderBy(F.desc("c"), "ans"))).filter("k = 1").select("target", "cue", "ans")
    scored = metrics.probe_scores(erasure.fit_table(pool, cues, support=SUPPORT), asked.filter("kind <> 'aa'").join(best, ["target", "cue"]))
    return metrics.grouped_scores(scored).select("target", "kind", r6("value").alias("value"))


# ---------------------------------------------------------------- memory similarity

FREQ = f"""{DIRECT}, {TRUTH}, f1 as (select target, 'flat' as generator, dst as entity, c as n from ca where c >= 6), fr as materialized (select * from f1 union all select target, 'direct_qa', entity, agreed from dq where kept union all select target, 'truth', entity, n from tr)"""


def frequencies(spark, d) -> DataFrame:
    pool, targets = star(spark, d, 4)
    own = baselines.hop_one(targets, pool, 20, 42).filter("c >= 6").select("target", F.lit("flat").alias("generator"), "entity", F.col("c").alias("n"))
    direct = baselines.direct_qa(targets, pool).filter("kept").select("target", F.lit("direct_qa").alias("generator"), "entity", F.col("agreed").alias("n"))
    truth = baselines.profile_truth(targets, pool).select("target", F.lit("truth").alias("generator"), "entity", "n")
    return own.unionByName(direct).unionByName(truth)


FBASE = f"with {sql.base('star_facts', 4, 'part:%')}, {FREQ}"
JACCARD = """tp as (select * from (select *, row_number() over (partition by target, generator order by n desc, entity) as k from fr) where k <= 50), sz as (select target, generator, count(*) as s from tp group by all),
    jc as (select x.target, x.generator as a, y.generator as b, coalesce((select count(*) from tp p join tp q on q.target = p.target and q.entity = p.entity where p.target = x.target and p.generator = x.generator and q.generator = y.generator), 0) as k, x.s as sa, y.s as sb from sz x join sz y on y.target = x.target)"""


@query(f"{FBASE}, {JACCARD} select target, a, b, round(k / (sa + sb - k), 6) as value from jc")
def entity_jaccard(spark, d):
    return metrics.entity_jaccard(frequencies(spark, d)).select("target", "a", "b", r6("value").alias("value"))


COSINE = """nm as (select target, generator, sqrt(sum(n * n)) as l from fr group by all), cs as (select x.target, x.generator as a, y.generator as b, coalesce((select sum(p.n * q.n) from fr p join fr q on q.target = p.target and q.entity = p.entity where p.target = x.target and p.generator = x.generator and q.generator = y.generator), 0) / (x.l * y.l) as value from nm x join nm y on y.target = x.target)"""


@query(f"{FBASE}, {COSINE} select target, a, b, round(value, 6) as value from cs")
def freq_cosine(spark, d):
    return metrics.freq_cosine(frequencies(spark, d)).select("target", "a", "b", r6("value").alias("value"))


@query(f"{FBASE}, {COSINE} select a, round(avg(value) filter (b = 'direct_qa'), 6) as direct_qa, round(avg(value) filter (b = 'flat'), 6) as flat, round(avg(value) filter (b = 'truth'), 6) as truth from cs group by a")
def similarity_matrix(spark, d):
    return metrics.similarity_matrix(metrics.freq_cosine(frequencies(spark, d)), ["direct_qa", "flat", "truth"])


@query(f"""{FBASE}, pf as (select distinct 'part:' || p_partkey as target, unnest(['name', 'brand', 'type']) as attribute, unnest(['name:' || p_name, 'brand:' || p_brand, 'type:' || p_type]) as value from part join targets on target = 'part:' || p_partkey),
    fd as (select distinct target, split_part(entity, ':', 1) as attribute, entity as value from f1) select p.target, p.attribute, count(distinct p.value) as facts, any_value(coalesce(f.n, 0)) > 0 as covered, round(2 * count(distinct h.value) / (count(distinct p.value) + any_value(coalesce(f.n, 0))), 6) as f1
    from pf p left join (select target, attribute, count(*) as n from fd group by all) f on f.target = p.target and f.attribute = p.attribute left join fd h on h.target = p.target and h.attribute = p.attribute and h.value = p.value group by p.target, p.attribute""")  # fmt: skip
def attribute_recovery(spark, d):
    pool, targets = star(spark, d, 4)
    found = baselines.hop_one(targets, pool, 20, 42).filter("c >= 6").select("target", F.substring_index("entity", ":", 1).alias("attribute"), F.col("entity").alias("value"))
    part = table(spark, d, "part").withColumn("target", F.concat(F.lit("part:"), F.col("p_partkey").cast("string"))).join(F.broadcast(targets), "target")  # four rows
    facts = part.select("target", F.explode(F.array(*[F.struct(F.lit(a).alias("attribute"), F.concat(F.lit(f"{a}:"), F.col(f"p_{a}")).alias("value")) for a in ("name", "brand", "type")])).alias("x")).select("target", "x.attribute", "x.value")
    return metrics.attribute_recovery(found, facts)


@query(_forget_sql("non_target", "qa") + """, nm as (select distinct target, unnest([obj, cue2]) as entity from q) select n.target, round(sum(case when nm.entity is not null then 1.0 else 0 end) / count(*), 6) as by_nodes,
    round(sum(case when nm.entity is not null then n.strength else 0 end) / sum(n.strength), 6) as by_strength from nodes n left join nm on nm.target = n.target and nm.entity = n.entity where n.hop > 0 group by n.target""")  # fmt: skip
def forget_coverage(spark, d):
    samples, g, _ = star_forget(spark, d)
    a = metrics.forget_coverage(samples, g.nodes).select("target", r6("coverage").alias("by_nodes"))
    return a.join(metrics.forget_coverage(samples, g.nodes, "strength").select("target", r6("coverage").alias("by_strength")), "target")


@query(f"""with {sql.base('basket_name', 2)}, f0 as (select target, target as anchor from targets), {sql.respond('f0', 'ra', 20)}, {sql.respond('f0', 'rb', 20, seed=43)}, {sql.strengths('ra', 'ca', 20, 1)}, {sql.strengths('rb', 'cb', 20, 1)},
    a as (select * from (select *, c / sum(c) over (partition by target, src) as w from ca) where c >= 4), b as (select * from (select *, c / sum(c) over (partition by target, src) as w from cb) where c >= 4),
    j as (select coalesce(a.target, b.target) as target, a.w as wa, b.w as wb from a full join b on b.target = a.target and b.dst = a.dst)
    select target, round(sum((wa is not null and wb is not null)::int) / count(*), 6) as jaccard, sum((wb is null)::int) as only_a, sum((wa is null)::int) as only_b, round(sum(abs(coalesce(wa, 0) - coalesce(wb, 0))), 6) as weight_l1 from j group by target""")  # fmt: skip
def graph_diff(spark, d):
    cfg = CFG.but(k=1)
    a, b = name_graph(spark, d, cfg), name_graph(spark, d, cfg.but(seed=43))
    return metrics.graph_diff(a.edges.filter("kept"), b.edges.filter("kept")).select("target", r6("jaccard").alias("jaccard"), "only_a", "only_b", r6("weight_l1").alias("weight_l1"))


# ---------------------------------------------------------------- reports

GRID = """gr as (select o_orderpriority as strategy, o_orderstatus as generator, case when o_custkey % 2 = 0 then 'forget' else 'neighbor' end as metric, cast(o_custkey % 5 as varchar) as target, avg(o_totalprice) as value from orders group by all)"""


def grid(spark, d) -> DataFrame:
    rows = table(spark, d, "orders").withColumn("metric", F.when(F.col("o_custkey") % 2 == 0, "forget").otherwise("neighbor")).withColumn("target", (F.col("o_custkey") % 5).cast("string"))
    return rows.groupBy(F.col("o_orderpriority").alias("strategy"), F.col("o_orderstatus").alias("generator"), "metric", "target").agg(F.avg("o_totalprice").alias("value"))


@query(f"with {GRID} select generator, strategy, metric, round(avg(value), 3) as value from gr where target in ('0', '1', '2') group by all")
def shared_target_avg(spark, d):
    shared = spark.createDataFrame([("0",), ("1",), ("2",), ("9",)], "target string")
    return metrics.shared_target_average(grid(spark, d), shared).select("generator", "strategy", "metric", F.round("value", 3).alias("value"))


@query(f"with {GRID}, v as (select strategy, generator, metric, round(avg(value), 2) as value from gr group by all), k as (select *, dense_rank() over (partition by strategy, metric order by case when metric = 'forget' then value else -value end) as mark from v) select strategy, generator, metric, value, case when mark <= 2 then mark end as mark from k")
def rank_marks(spark, d):
    rows = grid(spark, d).groupBy("strategy", "generator", "metric").agg(F.round(F.avg("value"), 2).alias("value"))
    return metrics.rank_marks(rows, ["forget"])


@query(f"with {GRID}, v as (select strategy, generator, metric, round(avg(value), 2) as value from gr group by all) select strategy, metric, round(max(value) filter (generator = 'F') - min(value) filter (generator in ('O', 'P')), 2) as gap from v group by all")
def supervision_gap(spark, d):
    rows = grid(spark, d).groupBy("strategy", "generator", "metric").agg(F.round(F.avg("value"), 2).alias("value"))
    return metrics.supervision_gap(rows, ["O", "P"], ours="F").select("strategy", "metric", F.round("gap", 2).alias("gap"))
