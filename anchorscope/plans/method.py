"""Queries of the method: elicitation, strength, expansion, walks, samples."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..config import RecallConfig
from ..functions import r6
from ..functions.session import cut
from ..operators import entities, recall, supervision, walks
from ..sources import carriers, responder, table
from ..sources.responder import PoolResponder
from . import BEFORE, query, sql

CFG = RecallConfig(n=20, tau=0.2, k=3, budget=None)
STAR = CFG.but(tau=0.3)
R, L = 20, 4
NAME_RECALL = sql.recall("basket_name", 2, 20, 4, 3)
STAR_RECALL = sql.recall("star_facts", 2, 20, 6, 3, like="part:%")


_POOLS: dict[tuple, DataFrame] = {}


def stamp(spark: SparkSession, d: str) -> int:
    """When a file of the tables last changed: what was derived from older ones isn't used again."""
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(d)
    fs = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return max((int(s.getModificationTime()) for s in fs.listStatus(folder)), default=0)


def forget_cached() -> None:
    """Drops what a session holds of pools and graphs, so that the next query pays for its own."""
    _POOLS.clear()
    _GRAPHS.clear()


def begin() -> None:
    """A query reads its own tables for its graphs and for the pool of names: only pools of facts and words are shared by the queries of a session."""
    _GRAPHS.clear()
    for key in [k for k in _POOLS if k[-1] == "basket_name"]:
        del _POOLS[key]


BEFORE.append(begin)


def indexed(spark: SparkSession, d: str, what: str, make) -> DataFrame:
    """A pool's mentions, written once a session to the shared folder: the index that all requests read."""
    key = (spark.sparkContext.applicationId, d, stamp(spark, d), what)
    if key not in _POOLS:
        _POOLS[key] = carriers.cut_pool(make(spark, d))
    return _POOLS[key]


def names(spark: SparkSession, d: str, n: int = 2) -> tuple[DataFrame, DataFrame]:
    pool = indexed(spark, d, "basket_name", lambda s, x: carriers.basket(s, x, "p_name"))
    return pool, carriers.frequent(pool, n)


def star(spark: SparkSession, d: str, n: int = 2) -> tuple[DataFrame, DataFrame]:
    pool = indexed(spark, d, "star_facts", carriers.star_facts)
    return pool, carriers.frequent(pool, n, "part:%")


_GRAPHS: dict[tuple, recall.RecallGraph] = {}


def reused(spark: SparkSession, d: str, what: str, cfg: RecallConfig, make) -> recall.RecallGraph:
    """A graph is built once a query, as its tables lie in the shared folder."""
    key = (spark.sparkContext.applicationId, d, stamp(spark, d), what, cfg)
    if key not in _GRAPHS:
        pool, targets = make(spark, d)
        _GRAPHS[key] = recall.expand(targets, PoolResponder(pool, n=cfg.n, seed=cfg.seed, conditioning=cfg.conditioning), cfg)
    return _GRAPHS[key]


def name_graph(spark: SparkSession, d: str, cfg: RecallConfig = CFG) -> recall.RecallGraph:
    return reused(spark, d, "basket_name", cfg, names)


def star_graph(spark: SparkSession, d: str, cfg: RecallConfig = STAR) -> recall.RecallGraph:
    return reused(spark, d, "star_facts", cfg, star)


def frontier(targets: DataFrame) -> DataFrame:
    return targets.select("target", F.col("target").alias("anchor"), F.lit(0).alias("hop"))


# ---------------------------------------------------------------- elicitation


def _elicit(conditioning: str):
    front = "f0 as (select t.target, b.entity as anchor from targets t join (select entity from pool group by entity order by count(*) desc, entity limit 4) b on true)"

    @query(f"with {sql.base('basket_name', 2)}, {front}, {sql.respond('f0', 'r', 20, conditioning)} select target, anchor, iter, record_id from r", name=f"elicit_conditioned_{conditioning}")
    def run(spark, d):
        pool, targets = names(spark, d)
        anchors = carriers.frequent(pool, 4).withColumnRenamed("target", "anchor")
        front = targets.crossJoin(anchors).withColumn("hop", F.lit(1))  # 2 x 4 rows
        return PoolResponder(pool, conditioning=conditioning).respond(front).select("target", "anchor", "iter", "record_id")


for _c in ("soft", "strict", "none"):
    _elicit(_c)


@query(f"with {sql.base('basket_name', 2)}, f0 as (select target, target as anchor from targets), {sql.respond('f0', 'r', 20)} select target, iter, record_id from r")
def elicit_hop0(spark, d):
    pool, targets = names(spark, d)
    return PoolResponder(pool).respond(frontier(targets)).select("target", "iter", "record_id")


@query(f"""with {sql.base('basket_name', 2)}, p as (select target, record_id, row_number() over (partition by target order by record_id) as at, count(*) over (partition by target) as n from pool join targets on entity = target),
    a as (select target, i as iter, 1 + floor({sql.draw('42', 'target', 'target', 'i')} * n) as at from (select distinct target, n from p), (select unnest(range(1, 21)) as i))
    select a.target, a.iter, p.record_id from a join p on p.target = a.target and p.at = a.at""")  # fmt: skip
def elicit_with_replacement(spark, d):
    pool, targets = names(spark, d)
    return PoolResponder(pool, replace=True).respond(frontier(targets)).select("target", "iter", "record_id")


@query(f"""with {sql.base('basket_part', 2)}, f0 as (select target, target as anchor from targets), {sql.respond('f0', 'r', 60)}
    select t.target, i.iter, r.record_id from targets t, (select unnest(range(1, 61)) as iter) i left join r on r.target = t.target and r.iter = i.iter""")  # fmt: skip
def elicit_short_pool(spark, d):
    pool = carriers.basket(spark, d, "l_partkey")
    who = PoolResponder(pool, n=60)
    return who.padded(who.respond(frontier(carriers.frequent(pool, 2)))).select("target", "iter", "record_id")


@query(f"""with l as ({sql.LINES}), k as (select min(record_id) as record_id from l where length(text) >= 20 group by md5(lower(trim(regexp_replace(text, ' +', ' ', 'g')))))
    select count(*) as records, (select count(*) from k) as kept from l where length(text) >= 20""")  # fmt: skip
def pool_dedup(spark, d):
    lines = carriers.doc_lines(spark, d).filter(F.length("text") >= 20)
    kept = responder.dedup_pool(lines.select("record_id"), lines)
    return lines.agg(F.count("*").alias("records")).crossJoin(kept.agg(F.count("*").alias("kept")))


@query("""select conv_id, turn, text as prompt, response from (select *, lead(role) over (partition by conv_id order by turn) as next_role, lead(text) over (partition by conv_id order by turn) as response from conversations)
    where role = 'user' and next_role = 'assistant'""")  # fmt: skip
def recorded_responses(spark, d):
    return responder.recorded(table(spark, d, "conversations"))


@query(f"""with {sql.base('basket_name', 2)} select t.target, b.entity as anchor, case when b.entity = t.target then 'List everything that you associate with ' || t.target || '.'
    else 'Thinking of ' || t.target || ': what do you recall about ' || b.entity || ' in that connection?' end as prompt from targets t, (select entity from pool group by entity order by count(*) desc, entity limit 4) b""")  # fmt: skip
def render_prompts(spark, d):
    pool, targets = names(spark, d)
    return responder.render_prompts(targets.crossJoin(carriers.frequent(pool, 4).withColumnRenamed("target", "anchor")))


@query(f"""with r as (select p_partkey as request_id, case when p_partkey % 2 = 0 then p_name else p_name || ' is a part of brand ' || p_brand || ' and type ' || p_type end as anchor_text from part)
    select request_id, trim(case when contains(anchor_text, ' is ') then split_part(anchor_text, ' is ', 1) else anchor_text end) as target, case when contains(anchor_text, ' is ') then 'description' else 'name' end as anchor_kind,
    array_to_string(list_sort(list_distinct(list_filter({sql.WORDS.format("case when contains(anchor_text, ' is ') then substr(anchor_text, instr(anchor_text, ' is ') + 4) else '' end")}, lambda w: length(w) >= 4))), ',') as terms from r""")  # fmt: skip
def anchor_forms(spark, d):
    text = F.when(F.col("p_partkey") % 2 == 0, F.col("p_name")).otherwise(F.concat("p_name", F.lit(" is a part of brand "), "p_brand", F.lit(" and type "), "p_type"))
    return entities.anchor_forms(table(spark, d, "part").select(F.col("p_partkey").alias("request_id"), text.alias("anchor_text")))


@query(f"with {sql.base('star_facts', 8, 'part:%')}, f0 as (select target, target as anchor from targets), {sql.respond('f0', 'r', 1)}, {sql.strengths('r', 'c', 1, 1)} select target, dst as entity from c")
def flat_recall(spark, d):
    from ..operators import baselines

    pool, targets = star(spark, d, 8)
    return baselines.flat_recall(targets, pool)


# ---------------------------------------------------------------- entities


@query(f"select entity, count(*) as df from (select distinct doc_id, unnest({sql.WORDS.format('text')}) as entity from documents) where length(entity) >= 6 group by entity having count(*) between 5 and 0.2 * (select count(*) from documents)")
def entity_lexicon(spark, d):
    return entities.build_lexicon(table(spark, d, "documents"))


@query(f"""with l as (select entity from (select distinct doc_id, unnest({sql.WORDS.format('text')}) as entity from documents) where length(entity) >= 6 group by entity having count(*) between 5 and 0.2 * (select count(*) from documents)),
    m as (select distinct doc_id, unnest({sql.WORDS.format('text')}) as entity from documents) select doc_id, entity from m semi join l using (entity)""")  # fmt: skip
def extract_mentions(spark, d):
    docs = table(spark, d, "documents")
    return entities.extract_mentions(docs, entities.build_lexicon(docs), keys=["doc_id"])


@query("""select lang, count(*) as words, sum(df) as mentions from (select lang, entity, count(*) as df from (select distinct doc_id, lang, unnest(list_transform(regexp_extract_all(text, '(\\p{L}+)', 1), lambda w: lower(w))) as entity from documents)
    where length(entity) >= 6 group by lang, entity having count(*) >= 3) join (select lang as l, count(*) as of from documents group by lang) on l is not distinct from lang where df <= 0.2 * of group by lang""")  # fmt: skip
def lexicon_by_lang(spark, d):
    rows = entities.build_lexicon(table(spark, d, "documents"), rule="letters", min_df=3, by="lang")
    return rows.groupBy("lang").agg(F.count("*").alias("words"), F.sum("df").alias("mentions"))


@query("select distinct cast(l_orderkey as varchar) as record_id, cast(l_partkey as varchar) as entity from lineitem")
def basket_mentions(spark, d):
    return entities.column_mentions(table(spark, d, "lineitem"), "l_orderkey", "l_partkey")


@query("select distinct cast(p_partkey as varchar) as record_id, unnest(['name:' || p_name, 'brand:' || p_brand, 'size:' || p_size]) as entity from part")
def typed_mentions(spark, d):
    return entities.typed_mentions(table(spark, d, "part"), "p_partkey", {"name": "p_name", "brand": "p_brand", "size": "p_size"})


@query("""with a as (select distinct trim(regexp_replace(lower(p_name), '[^a-z0-9]+', ' ', 'g')) as k, min(p_brand) over (partition by p_name) as canonical from part where p_name like 'red%')
    select distinct cast(p_partkey as varchar) as record_id, coalesce(a.canonical, trim(regexp_replace(lower(p_name), '[^a-z0-9]+', ' ', 'g'))) as entity from part left join a on a.k = trim(regexp_replace(lower(p_name), '[^a-z0-9]+', ' ', 'g'))""")  # fmt: skip
def alias_fold(spark, d):
    part = table(spark, d, "part")
    aliases = part.filter("p_name like 'red%'").groupBy(F.upper("p_name").alias("alias")).agg(F.min("p_brand").alias("canonical"))
    return entities.canonicalize(entities.column_mentions(part, "p_partkey", "p_name"), aliases)


# ---------------------------------------------------------------- strength and graph


@query(f"with {sql.base('basket_name', 2)}, f0 as (select target, target as anchor from targets), {sql.respond('f0', 'r', 20)}, {sql.strengths('r', 'c', 20, 1)} select target, dst as entity, c, s from c")
def mention_strength(spark, d):
    pool, targets = names(spark, d)
    who = PoolResponder(pool)
    return recall.mention_strength(who.extract(who.respond(frontier(targets))), n=20).select("target", "entity", "c", "s")


@query(f"with {sql.base('basket_name', 2)}, f0 as (select target, target as anchor from targets), {sql.respond('f0', 'r', 20)}, {sql.strengths('r', 'c', 20, 1)} select target, dst as entity, c from c where c >= 4")
def retained_one_hop(spark, d):
    return mention_strength(spark, d).filter(F.col("c") >= CFG.need).select("target", "entity", "c")


def _weights(norm: str, name: str):
    @query(f"with {sql.recall('basket_name', 2, 20, 4, 1, norm=norm)} select target, src, dst, c, round(w, 6) as w, kept from edges", name=name)
    def run(spark, d):
        return name_graph(spark, d, CFG.but(k=1, norm=norm)).edges.select("target", "src", "dst", "c", r6("w").alias("w"), "kept")


_weights("extracted", "edge_weights")
_weights("retained", "edge_weights_retained")


@query(f"with {NAME_RECALL} select target, entity, hop, round(strength, 6) as strength, c from nodes")
def recall_nodes_k3(spark, d):
    return name_graph(spark, d).nodes.select("target", "entity", "hop", r6("strength").alias("strength"), "c")


@query(f"with {NAME_RECALL} select target, src, dst, hop, c, round(w, 6) as w, kept from edges")
def recall_edges_k3(spark, d):
    return name_graph(spark, d).edges.select("target", "src", "dst", "hop", "c", r6("w").alias("w"), "kept")


def _carrier(name: str, pool, n: int, need: int, k: int, like: str | None = None):
    @query(f"with {sql.recall(name, 1, n, need, k, like=like)} select target, src, dst, hop, c, round(w, 6) as w from edges where kept", name=f"recall_{name}")
    def run(spark, d):
        p = indexed(spark, d, name, pool)
        g = recall.expand(carriers.frequent(p, 1, like), PoolResponder(p, n=n), RecallConfig(n=n, tau=need / n, k=k, budget=None))
        return g.edges.filter("kept").select("target", "src", "dst", "hop", "c", r6("w").alias("w"))


_carrier("star_facts", carriers.star_facts, 20, 6, 3, "part:%")
_carrier("customer_facts", carriers.customer_facts, 10, 5, 2, "cust:%")
_carrier("basket_brand", lambda s, d: carriers.basket(s, d, "p_brand"), 20, 5, 3)
_carrier("basket_part", lambda s, d: carriers.basket(s, d, "l_partkey"), 20, 2, 3)
_carrier("hour_users", carriers.hour_users, 20, 4, 2)
_carrier("doc_words", carriers.doc_words, 20, 3, 2)
_carrier("dialog_words", carriers.dialog_words, 20, 6, 2)


@query(f"with {NAME_RECALL} select target, dst as entity, round(avg(s), 6) as mean_s, round(max(s), 6) as max_s, round(arg_min(s, [lpad(cast(hop as varchar), 3, '0'), src]), 6) as first_s from edges where kept group by target, dst")
def node_strength_agg(spark, d):
    kept = name_graph(spark, d).edges.filter("kept")
    return kept.groupBy("target", F.col("dst").alias("entity")).agg(r6(F.avg("s")).alias("mean_s"), r6(F.max("s")).alias("max_s"), r6(F.min_by("s", F.struct("hop", "src"))).alias("first_s"))


@query(f"with {NAME_RECALL} select e.target, e.src, e.dst, e.hop, r.hop as first_hop, e.c from edges e join nodes r on r.target = e.target and r.entity = e.dst where e.kept and r.hop < e.hop")
def back_edges(spark, d):
    return recall.back_edges(name_graph(spark, d))


@query(f"with {sql.recall('basket_name', 2, 20, 4, 3, budget=6)} select target, src, dst, hop, c from edges where kept")
def recall_budgeted(spark, d):
    return name_graph(spark, d, CFG.but(budget=6)).edges.filter("kept").select("target", "src", "dst", "hop", "c")


PROFILE = """select n.target, count(*) as nodes, max(hop) as max_hop, any_value(coalesce(e.edges, 0)) as edges, round(any_value(e.out_degree), 6) as out_degree,
    round(case when count(*) > 1 then any_value(e.edges) / (count(*) * (count(*) - 1)) end, 6) as density, round(any_value(e.h), 6) as weight_entropy from nodes n left join
    (select target, sum(deg) as edges, avg(deg) as out_degree, avg(h) as h from (select target, src, count(*) as deg, -sum(p * log2(p)) as h from
        (select target, src, c / sum(c) over (partition by target, src) as p from edges where kept) group by target, src) group by target) e on e.target = n.target group by n.target"""


@query(f"with {NAME_RECALL} {PROFILE}")
def graph_profile(spark, d):
    return recall.graph_profile(name_graph(spark, d))


@query(f"""with {sql.base('basket_name', 2)}, f0 as (select target, target as anchor from targets), {sql.respond('f0', 'r1', 20)}, {sql.respond('f0', 'r2', 20, seed=43)}, {sql.strengths('r1', 'a', 20, 1)}, {sql.strengths('r2', 'b', 20, 1)}
    select target, dst as entity, sum(c) as c, count(*) * 20 as n, round(sum(c) / (count(*) * 20), 6) as s from (select * from a union all select * from b) group by target, dst""")  # fmt: skip
def strength_merge(spark, d):
    pool, targets = names(spark, d)
    rounds = []
    for seed in (42, 43):
        who = PoolResponder(pool, seed=seed)
        rounds.append(recall.mention_strength(who.extract(who.respond(frontier(targets))), n=20).select("target", "anchor", "entity", "c", F.lit(20).cast("long").alias("n")))
    return recall.merge_strength(*rounds).select("target", "entity", "c", "n", r6("s").alias("s"))


@query(f"""with {NAME_RECALL} select n.target, sum(i) as iterations, sum(i) * 20 as calls, any_value(v) as nodes, round(sum(i) / any_value(v), 6) as iterations_per_node from
    (select target, src, 1 as i from edges group by target, src) n join (select target, count(*) as v from nodes group by target) m on m.target = n.target group by n.target""")  # fmt: skip
def recall_overhead(spark, d):
    g = name_graph(spark, d)
    return recall.recall_overhead(g.log, g.nodes)


# ---------------------------------------------------------------- walks


@query(f"""with {NAME_RECALL}, v as (select target, entity, row_number() over (partition by target order by entity) - 1 as visits from nodes), t as (select e.target, e.src, e.dst, e.w * pow(1 / (1 + v.visits), 1.0) as x
    from edges e join v on v.target = e.target and v.entity = e.dst where e.kept) select target, src, dst, round(x / sum(x) over (partition by target, src), 6) as p from t""")  # fmt: skip
def transition_probs(spark, d):
    g = name_graph(spark, d)
    visits = g.nodes.select("target", "entity", (F.row_number().over(Window.partitionBy("target").orderBy("entity")) - 1).alias("visits"))
    return walks.transition_probs(g.edges.filter("kept"), visits, 1.0).select("target", "src", "dst", r6("p").alias("p"))


@query(f"""with {NAME_RECALL}, v as (select target, entity, row_number() over (partition by target order by entity) - 1 as visits from nodes), t as (select a.alpha, e.target, e.src, e.dst, e.w * pow(1 / (1 + v.visits), a.alpha) as x
    from edges e join v on v.target = e.target and v.entity = e.dst, (select unnest([0.0::double, 0.5::double, 1.0::double, 2.0::double]) as alpha) a where e.kept), q as (select *, x / sum(x) over (partition by alpha, target, src) as p from t)
    select alpha, target, src, round(-sum(p * log2(p)), 6) + 0.0 as entropy from q group by alpha, target, src""")  # fmt: skip
def transition_alpha_grid(spark, d):
    g = name_graph(spark, d)
    visits = g.nodes.select("target", "entity", (F.row_number().over(Window.partitionBy("target").orderBy("entity")) - 1).alias("visits"))
    rows = None
    for alpha in (0.0, 0.5, 1.0, 2.0):
        one = walks.transition_probs(g.edges.filter("kept"), visits, alpha).withColumn("alpha", F.lit(alpha))
        rows = one if rows is None else rows.unionByName(one)
    return rows.groupBy("alpha", "target", "src").agg((r6(-F.sum(F.col("p") * F.log2("p"))) + 0.0).alias("entropy"))


def star_steps(spark, d, weighting: str = "strength") -> tuple[recall.RecallGraph, DataFrame]:
    g = star_graph(spark, d)
    starts = g.nodes.filter("hop = 0").select("target", F.col("entity").alias("node"))
    return g, walks.walk_rounds(g.edges, starts, r=R, l=L, weighting=weighting)


WALKS = f"{STAR_RECALL}, {sql.walk_steps(R, L)}"


def _rounds(weighting: str, name: str):
    @query(f"with {STAR_RECALL}, {sql.walk_steps(R, L, weighting=weighting)} select target, walk_id, step, node from steps", name=name)
    def run(spark, d):
        return star_steps(spark, d, weighting)[1].select("target", "walk_id", "step", "node")


_rounds("strength", "walks_rounds_alpha0")
_rounds("uniform", "walks_uniform")


@query(f"with {WALKS} select target, walk_id, array_to_string(nodes, ' > ') as path, len(weights) as n_edges, round(quality, 6) as quality from paths")
def path_quality(spark, d):
    return walks.paths_of(star_steps(spark, d)[1]).select("target", "walk_id", F.array_join("nodes", " > ").alias("path"), F.col("n_edges").cast("long").alias("n_edges"), r6("quality").alias("quality"))


@query(f"with {WALKS} select target, walk_id from paths where quality >= 0.05")
def kept_paths(spark, d):
    return walks.filter_paths(walks.paths_of(star_steps(spark, d)[1]), 0.05).select("target", "walk_id")


@query(f"with {WALKS} select target, walk_id from paths qualify quality >= quantile_cont(quality, 0.25) over (partition by target) - 1e-12")
def kept_paths_quantile(spark, d):
    return walks.filter_paths(walks.paths_of(star_steps(spark, d)[1]), 0.25, "quantile").select("target", "walk_id")


@query(f"with {WALKS} select target, array_to_string(nodes, ' > ') as path, count(*) as n from paths group by all")
def path_multiplicity(spark, d):
    return walks.paths_of(star_steps(spark, d)[1]).groupBy("target", F.array_join("nodes", " > ").alias("path")).agg(F.count("*").alias("n"))


def _expected(l: int) -> str:  # noqa: E741
    parts = ["p as materialized (select target, src, dst, w / sum(w) over (partition by target, src) as p from edges where kept)", "x0 as (select target, target as entity, 1.0 as visits from targets)"]
    parts += [f"x{i + 1} as materialized (select x.target, p.dst as entity, sum(x.visits * p.p) as visits from x{i} x join p on p.target = x.target and p.src = x.entity group by x.target, p.dst)" for i in range(l)]
    return ", ".join(parts) + ", ev as (select target, entity, sum(visits) as visits from (" + " union all ".join(f"select * from x{i}" for i in range(l + 1)) + ") group by target, entity)"


@query(f"with {STAR_RECALL}, {_expected(L)} select target, entity, round(visits, 6) as visits from ev")
def expected_visits(spark, d):
    g = star_graph(spark, d)
    return walks.expected_visits(g.edges, g.nodes.filter("hop = 0").select("target", F.col("entity").alias("node")), L).select("target", "entity", r6("visits").alias("visits"))


@query(f"""with {STAR_RECALL}, {_expected(L)}, t as (select n.target, round(coalesce(v.visits, 0), 9) as x, round(n.strength, 9) as y from nodes n left join ev v on v.target = n.target and v.entity = n.entity where n.hop > 0),
    k as (select target, rank() over (partition by target order by x) + (count(*) over (partition by target, x) - 1) / 2 as x, rank() over (partition by target order by y) + (count(*) over (partition by target, y) - 1) / 2 as y from t)
    select target, round(corr(x, y), 6) as rank_corr from k group by target""")  # fmt: skip
def salience_corr(spark, d):
    from ..metrics import salience_corr as measure

    g = star_graph(spark, d)
    visits = walks.expected_visits(g.edges, g.nodes.filter("hop = 0").select("target", F.col("entity").alias("node")), L)
    return measure(visits, g.nodes).select("target", r6("rank_corr").alias("rank_corr"))


@query()
def forget_walks(spark, d):
    g = star_graph(spark, d)
    return walks.sample_walks(g.edges, g.nodes, STAR).select("target", "walk_id", F.array_join("nodes", " > ").alias("path"), r6("quality").alias("quality"))


@query()
def neighbor_walks(spark, d):
    g = star_graph(spark, d)
    return walks.sample_walks(g.edges, g.nodes, STAR, "neighbor").select("target", "walk_id", F.array_join("nodes", " > ").alias("path"), r6("quality").alias("quality"))


# ---------------------------------------------------------------- samples


NEIGHBOR_WALKS = f"{STAR_RECALL}, " + sql.walk_steps(
    R, L, role="neighbor", starts="select target, entity as node from (select *, row_number() over (partition by target order by strength desc, entity) as place from nodes where hop = 1 and strength >= 0.3 - 1e-12) where place = 1",
    where="kept and src <> target and dst <> target",
)


def star_pairs(spark, d, role: str = "forget") -> tuple[DataFrame, recall.RecallGraph, DataFrame]:
    pool, _ = star(spark, d)
    if role == "forget":
        g, steps = star_steps(spark, d)
    else:
        g = star_graph(spark, d)
        at = F.row_number().over(Window.partitionBy("target").orderBy(F.desc("strength"), "entity"))
        starts = g.nodes.filter("hop = 1 and strength >= 0.3 - 1e-12").withColumn("at", at).filter("at = 1").select("target", F.col("entity").alias("node"))
        steps = walks.walk_rounds(g.edges.filter("src <> target and dst <> target"), starts, r=R, l=L, role="neighbor")
    return supervision.path_pairs(walks.paths_of(steps, role)), g, pool


PAIRS = """pairs as materialized (select target, walk_id, i - 1 as pos, nodes[i] as l, nodes[i + 1] as r, weights[i] as w, nodes[1] as origin from (select *, unnest(range(1, len(nodes))) as i from paths)),
    stated as materialized (select p.target, p.l, p.r, arg_min(a.record_id, [case when t.record_id is null then '1' else '0' end, lpad(cast(length(a.record_id) as varchar), 9, '0'), a.record_id]) as evidence_id, p.l || ' goes with ' || p.r as statement
        from (select distinct target, l, r from pairs) p left join (pool a join pool b on a.record_id = b.record_id) on a.entity = p.l and b.entity = p.r left join pool t on t.entity = p.target and t.record_id = a.record_id group by p.target, p.l, p.r)"""


@query(f"with {WALKS}, {PAIRS} select target, walk_id, pos, l as \"left\", r as \"right\", round(w, 6) as w from pairs")
def path_pairs(spark, d):
    return star_pairs(spark, d)[0].select("target", "walk_id", "pos", "left", "right", r6("w").alias("w"))


@query(f"with {WALKS}, {PAIRS} select target, l as \"left\", r as \"right\", evidence_id, statement from stated")
def event_statements(spark, d):
    pairs, _, pool = star_pairs(spark, d)
    return supervision.event_statements(pairs, pool)


def _forget_sql(rule: str, style: str) -> str:
    leak = "p.l = p.target" if rule == "non_target" else "false"
    q = {"qa": "'Which entity is tied to ' || obj || case when cue2 is not null and cue2 <> obj and cue2 <> answer then ' and ' || cue2 else '' end || '?'", "cloze": "'____ goes with ' || obj"}[style]
    return f"""with {WALKS}, {PAIRS}, s as (select p.target, walk_id, pos, case when {leak} then p.r else p.l end as obj, case when {leak} then null else p.r end as cue2, p.target as answer, evidence_id from pairs p join stated t on t.target = p.target and t.l = p.l and t.r = p.r),
    q as (select md5(target || '|forget|graph_recall|' || walk_id || '|' || pos || '|' || obj || '|' || answer) as sample_id, *, {q} as question from s)"""


COLUMNS = "sample_id, target, question, obj, answer, evidence_id"


@query(_forget_sql("non_target", "qa") + f" select {COLUMNS} from q")
def forget_samples(spark, d):
    pairs, _, pool = star_pairs(spark, d)
    return supervision.forget_samples(pairs, supervision.event_statements(pairs, pool)).select(*COLUMNS.split(", "))


@query(_forget_sql("literal", "qa") + f" select {COLUMNS} from q")
def forget_obj_rule(spark, d):
    pairs, _, pool = star_pairs(spark, d)
    return supervision.forget_samples(pairs, supervision.event_statements(pairs, pool), obj_rule="literal").select(*COLUMNS.split(", "))


@query(_forget_sql("non_target", "cloze") + f" select {COLUMNS} from q")
def forget_cloze(spark, d):
    pairs, _, pool = star_pairs(spark, d)
    return supervision.forget_samples(pairs, supervision.event_statements(pairs, pool), style="cloze").select(*COLUMNS.split(", "))


def star_forget(spark, d) -> tuple[DataFrame, recall.RecallGraph, DataFrame]:
    pairs, g, pool = star_pairs(spark, d)
    return supervision.forget_samples(pairs, supervision.event_statements(pairs, pool)), g, pool


@query(_forget_sql("non_target", "qa") + " select sample_id, length(question) + 1 as span_start, length(question) + 1 + length(answer) as span_end, len(string_split(question, ' ')) as masked, len(string_split(answer, ' ')) as counted from q")
def answer_span(spark, d):
    rows = supervision.answer_mask(star_forget(spark, d)[0])
    ones = F.aggregate("loss_mask", F.lit(0), lambda s, x: s + x)
    return rows.select("sample_id", F.col("span.start").cast("long").alias("span_start"), F.col("span.end").cast("long").alias("span_end"), (F.size("loss_mask") - ones).cast("long").alias("masked"), ones.cast("long").alias("counted"))


NEIGHBOR_SQL = f"""with {NEIGHBOR_WALKS}, {PAIRS}, s as (select p.target, walk_id, pos, origin as answer, case when p.l = origin then p.r else p.l end as obj, case when p.l = origin then null else p.r end as cue2, evidence_id
    from pairs p join stated t on t.target = p.target and t.l = p.l and t.r = p.r), f as (select * from s where obj <> target and coalesce(cue2, '') <> target and obj <> answer),
    q as (select md5(target || '|neighbor|graph_recall|' || walk_id || '|' || pos || '|' || obj || '|' || answer) as sample_id, *, 'Which entity is tied to ' || obj || case when cue2 is not null and cue2 <> obj and cue2 <> answer then ' and ' || cue2 else '' end || '?' as question from f)"""


def star_neighbor(spark, d) -> DataFrame:
    pairs, _, pool = star_pairs(spark, d, "neighbor")
    return supervision.neighbor_samples(pairs, supervision.event_statements(pairs, pool))


@query(NEIGHBOR_SQL + f" select {COLUMNS} from q")
def neighbor_samples(spark, d):
    return star_neighbor(spark, d).select(*COLUMNS.split(", "))


@query(_forget_sql("literal", "qa") + """, a as (select obj, cue2, count(distinct answer) as answers from q group by obj, cue2)
    select q.target, case when contains(question, answer) then 'leak' when answers > 1 then 'ambiguous' else 'ok' end as reason, count(*) as n from q join a on a.obj = q.obj and a.cue2 is not distinct from q.cue2 group by all""")  # fmt: skip
def sample_guard(spark, d):
    pairs, _, pool = star_pairs(spark, d)
    rows = supervision.forget_samples(pairs, supervision.event_statements(pairs, pool), obj_rule="literal")
    return supervision.validate_samples(rows).groupBy("target", "reason").agg(F.count("*").alias("n"))


@query()
def scope_disjoint(spark, d):
    return supervision.scope_report(star_forget(spark, d)[0].unionByName(star_neighbor(spark, d)))


@query(f"""with {STAR_RECALL}, b as (select distinct p.record_id, n.target from pool p join nodes n on n.entity = p.entity), a as (select t.target, r.record_id from targets t, (select distinct record_id from pool) r anti join b on b.target = t.target and b.record_id = r.record_id)
    select target, record_id, \"at\" from (select *, row_number() over (partition by target order by {sql.draw('42', 'record_id')}, record_id) as \"at\" from a) where \"at\" <= 20""".replace("from targets t, (select distinct record_id from pool) r anti join b on b.target = t.target and b.record_id = r.record_id", "from targets t, (select distinct record_id from pool) r where not exists (select 1 from b where b.target = t.target and b.record_id = r.record_id)"))  # fmt: skip
def retain_samples(spark, d):
    g = star_graph(spark, d)
    return supervision.retain_samples(star(spark, d)[0], g.nodes, 20)


@query(_forget_sql("non_target", "qa") + f""" select target, sample_id, row_number() over (partition by target order by {sql.draw('42', 'sample_id')}, sample_id) as "at",
    '{{"question":"' || question || '","answer":"' || answer || '","role":"forget"}}' as line from q""")  # fmt: skip
def samples_json(spark, d):
    return supervision.samples_json(star_forget(spark, d)[0])


@query(_forget_sql("non_target", "qa") + """, rs as (select target, anchor, p.entity, arg_min(r.record_id, r.iter) as response_id from (select * from r0 union all select * from r1 union all select * from r2) r join pool p on p.record_id = r.record_id group by target, anchor, p.entity)
    select q.sample_id, e.target, e.src, e.dst, e.c, rs.response_id from q join edges e on e.target = q.target and e.dst = q.obj left join rs on rs.target = e.target and rs.anchor = e.src and rs.entity = e.dst where e.kept""")  # fmt: skip
def audit_trail(spark, d):
    samples, g, pool = star_forget(spark, d)
    anchors = g.edges.select("target", F.col("src").alias("anchor"), F.lit(0).alias("hop")).distinct()
    return supervision.audit_trail(samples, g.edges, PoolResponder(pool).respond(anchors), pool)


FORGET_TEXTS = f"""t as (select target, text from ({sql.LINES}) l, (select entity as target from ({sql.POOLS['doc_words']}) group by entity order by count(*) desc, entity limit 3) w where length(text) >= 20 and contains(lower(text), target) union all select 'thing', text from documents)"""


def forget_texts(spark, d) -> DataFrame:
    lines = carriers.doc_lines(spark, d).filter(F.length("text") >= 20)
    targets = carriers.frequent(carriers.doc_words(spark, d), 3)
    hit = lines.join(F.broadcast(targets), F.contains(F.lower("text"), F.col("target"))).select("target", "text")  # three rows
    return hit.unionByName(table(spark, d, "documents").select(F.lit("thing").alias("target"), "text"))


@query(f"""with {FORGET_TEXTS}, bw as (select {sql.WORDS.format('text')} as w from benchmark), k as (select distinct n, array_to_string(w[i : i + n - 1], ' ') as gram from (select w, least(10, len(w)) as n, unnest(range(1, len(w) - least(10, len(w)) + 2)) as i from bw where len(w) > 0)),
    tw as (select target, text, {sql.WORDS.format('text')} as w from (select distinct target, text from t)), h as (select distinct target, text from (select target, text, n, array_to_string(w[i : i + n - 1], ' ') as gram from (select target, text, w, n, unnest(range(1, len(w) - n + 2)) as i from tw, (select distinct n from k) where len(w) >= n)) join k using (n, gram))
    select t.target, count(*) as n, sum(case when contains(lower(t.text), lower(t.target)) then 0 else 1 end) as off_topic, count(*) - count(distinct t.text) as copies, count(h.text) as planted,
    sum(case when regexp_matches(t.text, '[a-zA-Z0-9._]+@[a-zA-Z0-9.]+') or regexp_matches(t.text, '[0-9]{{7,}}') then 1 else 0 end) as personal from t left join h on h.target = t.target and h.text = t.text group by t.target""")  # fmt: skip
def forget_set_audit(spark, d):
    return supervision.audit_forget_set(forget_texts(spark, d), table(spark, d, "benchmark"))


@query(f"with {FORGET_TEXTS} select target, sum(length(text)) as chars_texts, length(target) as chars_anchor, sum(len(regexp_extract_all(text, '[a-zA-Z0-9._]+@[a-zA-Z0-9.]+|[0-9]{{7,}}'))) as personal_hits from t group by target")
def request_exposure(spark, d):
    return supervision.request_exposure(forget_texts(spark, d))


@query("""with r as (select p_partkey as request_id, case p_partkey % 4 when 0 then p_name when 1 then '' when 2 then 'no such thing' else p_brand end as target from part),
    a as (select p_brand as target, count(distinct p_type) as meanings from part group by p_brand), k as (select distinct p_name as target from part join lineitem on l_partkey = p_partkey)
    select request_id, case when r.target = '' then 'empty' when coalesce(a.meanings, 0) > 1 then 'ambiguous' when k.target is null and coalesce(a.meanings, 0) = 0 then 'unknown' else 'ok' end as reason
    from r left join a on a.target = r.target left join k on k.target = r.target""")  # fmt: skip
def request_validation(spark, d):
    part = table(spark, d, "part")
    ask = F.when(F.col("p_partkey") % 4 == 0, F.col("p_name")).when(F.col("p_partkey") % 4 == 1, "").when(F.col("p_partkey") % 4 == 2, "no such thing").otherwise(F.col("p_brand"))
    aliases = part.select(F.col("p_brand").alias("alias"), F.col("p_type").alias("canonical")).distinct()
    return entities.validate_request(part.select(F.col("p_partkey").alias("request_id"), ask.alias("target")), carriers.basket(spark, d, "p_name"), aliases)


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """The whole method on the most frequent part: guarded forget and neighbour samples."""
    from ..api import graph_recall

    pool, targets = star(spark, d, 1)
    done = graph_recall(targets, pool, STAR.but(budget=200))
    return supervision.validate_samples(done.forget.unionByName(done.neighbor)).select("sample_id", "target", "role", "question", "answer", "evidence_id", "reason")
