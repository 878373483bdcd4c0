"""Queries of the relational surface: scans, joins, aggregates, windows, sets, samples, strings, arrays, SQL functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import r6, words
from ..operators import relational as ops
from ..sources import carriers, table
from . import query, sql
from .method import name_graph, names


@query("select doc_id, lang, source from documents where lang = 'en' and n_chars between 200 and 2000")
def scan_documents(spark, d):
    return table(spark, d, "documents").filter("lang = 'en' and n_chars between 200 and 2000").select("doc_id", "lang", "source")


@query("select event_id, cast(json_extract_string(props, '$.k') as int) as k from events")
def events_props(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("select doc_id, source is not distinct from 'src3' as is_src3, text like '%the%' as has_the, regexp_matches(text, '[0-9]{4}') as has_year from documents where lang in ('en', 'de')")
def project_filter_lang(spark, d):
    return table(spark, d, "documents").filter(F.col("lang").isin("en", "de")).select("doc_id", F.col("source").eqNullSafe("src3").alias("is_src3"), F.col("text").like("%the%").alias("has_the"), F.col("text").rlike("[0-9]{4}").alias("has_year"))


@query("select p_brand, count(*) as n, cast(sum(cast(l_extendedprice as decimal(18,2))) as double) as revenue from lineitem join part on l_partkey = p_partkey group by p_brand")
def join_order_part(spark, d):
    part = table(spark, d, "part").select("p_partkey", "p_brand")
    lines = table(spark, d, "lineitem").select("l_partkey", "l_extendedprice")
    return lines.join(part, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("n"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("revenue"))


@query("select o_orderkey, count(*) as n_lines, round(max(l_quantity), 2) as most from orders join lineitem on o_orderkey = l_orderkey group by o_orderkey")
def join_orders_lineitem(spark, d):
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_quantity")
    return table(spark, d, "orders").select("o_orderkey").join(lines.hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.count("*").alias("n_lines"), F.round(F.max("l_quantity"), 2).alias("most"))


@query("""with a as (select l_partkey as k, count(*) as n from lineitem where l_returnflag = 'R' group by 1), b as (select l_partkey as k, count(*) as n from lineitem where l_linestatus = 'O' and l_returnflag = 'N' group by 1)
    select coalesce(a.k, b.k) as k, coalesce(a.n, 0) as a, coalesce(b.n, 0) as b from a full join b on a.k = b.k""")  # fmt: skip
def full_outer_freq(spark, d):
    lines = table(spark, d, "lineitem")
    a = lines.filter("l_returnflag = 'R'").groupBy(F.col("l_partkey").alias("k")).agg(F.count("*").alias("a"))
    b = lines.filter("l_linestatus = 'O' and l_returnflag = 'N'").groupBy(F.col("l_partkey").alias("k")).agg(F.count("*").alias("b"))
    return a.join(b, "k", "full_outer").na.fill(0)


@query(f"with {sql.base('basket_name', 1)} select distinct record_id from pool where record_id in (select record_id from pool join targets on entity = target)")
def semi_target_docs(spark, d):
    pool, targets = names(spark, d, 1)
    aim = pool.join(targets, pool["entity"] == targets["target"], "left_semi").select("record_id")
    return pool.select("record_id").distinct().join(aim, "record_id", "left_semi")


@query(f"with {sql.base('basket_name', 1)} select distinct record_id from pool where record_id not in (select record_id from pool join targets on entity = target)")
def anti_visited(spark, d):
    pool, targets = names(spark, d, 1)
    aim = pool.join(targets, pool["entity"] == targets["target"], "left_semi").select("record_id")
    return pool.select("record_id").distinct().join(aim, "record_id", "left_anti")


@query(f"with pool as ({sql.POOLS['basket_brand']}) select a.entity as a, b.entity as b, count(*) as n from pool a join pool b on a.record_id = b.record_id and a.entity < b.entity group by all")
def co_mention_pairs(spark, d):
    pool = carriers.basket(spark, d, "p_brand")
    a, b = pool.withColumnRenamed("entity", "a"), pool.withColumnRenamed("entity", "b")
    return a.join(b, "record_id").filter("a < b").groupBy("a", "b").agg(F.count("*").alias("n"))


@query("select a.p_partkey as a, b.p_partkey as b from part a join part b on b.p_retailprice >= a.p_retailprice and b.p_retailprice < a.p_retailprice + 1.0 and a.p_partkey <> b.p_partkey where a.p_size = 7")
def band_price_parts(spark, d):
    part = table(spark, d, "part")
    left = part.filter("p_size = 7").select(F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("low"))
    right = part.select(F.col("p_partkey").alias("b"), F.col("p_retailprice").alias("price"))
    return ops.band_join(left, right, F.col("low"), F.col("price"), 1.0).filter("a <> b").select("a", "b")


@query("select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour and a.event_id <> b.event_id")
def interval_events(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    return ops.interval_join(e.withColumnRenamed("event_id", "a"), e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("r_ts")), "user_id", "ts", 3600).filter("a <> b").select("a", "b")


@query("select p.event_id, v.event_id as asof from (select * from events where event_type = 'purchase') p asof left join (select user_id, ts, max(event_id) as event_id from events where event_type = 'view' group by user_id, ts) v on p.user_id = v.user_id and p.ts >= v.ts")
def asof_last_view(spark, d):
    e = table(spark, d, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type")
    views = e.filter("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("v"))
    return ops.asof_last(e.filter("event_type = 'purchase'").select("user_id", "ts", "event_id"), views, "user_id", "ts", "v").select("event_id", "asof")


@query("select a.status, b.priority, c.kind from (select distinct o_orderstatus as status from orders) a, (select distinct o_orderpriority as priority from orders) b, (select distinct event_type as kind from events) c")
def grid_cross(spark, d):
    """A grid of all values that the columns of the tables have, few each."""
    values = lambda name, column, alias: table(spark, d, name).select(F.col(column).alias(alias)).distinct()
    return values("orders", "o_orderstatus", "status").crossJoin(values("orders", "o_orderpriority", "priority")).crossJoin(values("events", "event_type", "kind"))


@query(f"select doc_id, w as word, count(*) as n from (select doc_id, unnest({sql.WORDS.format('text')}) as w from documents ) where length(w) > 9 group by all")
def lateral_tokens(spark, d):
    table(spark, d, "documents").select("doc_id", words(F.col("text")).alias("ws"), "lang").createOrReplaceTempView("_lateral_docs")
    return spark.sql("select doc_id, w as word, count(*) as n from _lateral_docs lateral view explode(ws) t as w where length(w) > 9 group by doc_id, w")


@query("""select event_type, count(*) as n, count(distinct user_id) as users, round(quantile_cont(value, 0.5), 6) as median, round(corr(value, cast(user_id as double)), 6) as corr, arg_min(event_id, [value, event_id]) as least, count(*) filter (value > 50) as high,
    array_to_string(list_sort(list(distinct user_id % 5)), ',') as kinds from events group by event_type""")  # fmt: skip
def aggregates_events(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(
        F.count("*").alias("n"), F.count_distinct("user_id").alias("users"), r6(F.percentile("value", F.lit(0.5))).alias("median"), r6(F.corr("value", F.col("user_id").cast("double"))).alias("corr"),
        F.min_by("event_id", F.struct("value", "event_id")).alias("least"), F.count_if(F.col("value") > 50).alias("high"), F.array_join(F.array_sort(F.collect_set(F.col("user_id") % 5)), ",").alias("kinds"),
    )


@query("with " + sql.recall("basket_name", 2, 20, 4, 3) + " select target, hop, count(*) as n, sum(c) as c from edges group by rollup (target, hop)")
def rollup_graph(spark, d):
    return name_graph(spark, d).edges.rollup("target", "hop").agg(F.count("*").alias("n"), F.sum("c").alias("c"))


@query("select event_type, user_id % 3 as g, count(*) as n from events group by cube (event_type, user_id % 3)")
def cube_events(spark, d):
    return table(spark, d, "events").withColumn("g", F.col("user_id") % 3).cube("event_type", "g").agg(F.count("*").alias("n"))


@query("select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def grouping_sets_orders(spark, d):
    return table(spark, d, "orders").groupingSets([[F.col("o_orderstatus")], [F.col("o_orderpriority")], []], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("select o_orderpriority as strategy, count(*) filter (o_orderstatus = 'F') as f, count(*) filter (o_orderstatus = 'O') as o, count(*) filter (o_orderstatus = 'P') as p from orders group by 1")
def pivot_scores(spark, d):
    rows = table(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("strategy")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return rows.na.fill(0).select("strategy", F.col("F").alias("f"), F.col("O").alias("o"), F.col("P").alias("p"))


@query("select p_partkey, metric, value from (select p_partkey, cast(p_size as double) as size, p_retailprice as price from part) unpivot (value for metric in (size, price))")
def unpivot_scores(spark, d):
    rows = table(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return rows.unpivot("p_partkey", ["size", "price"], "metric", "value")


@query("""select event_id, row_number() over w as rn, rank() over v as rk, dense_rank() over v as dr, round(percent_rank() over v, 6) as pr, ntile(4) over w as nt, lag(event_id) over w as lg, first_value(event_id) over w as fv,
    round(sum(value) over (w rows between 2 preceding and current row), 4) as s3 from events window w as (partition by user_id order by ts, event_id), v as (partition by user_id order by event_type)""")  # fmt: skip
def windows_events(spark, d):
    w, v = Window.partitionBy("user_id").orderBy("ts", "event_id"), Window.partitionBy("user_id").orderBy("event_type")
    return table(spark, d, "events").select(
        "event_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("rk"), F.dense_rank().over(v).cast("long").alias("dr"), r6(F.percent_rank().over(v)).alias("pr"), F.ntile(4).over(w).cast("long").alias("nt"),
        F.lag("event_id").over(w).alias("lg"), F.first("event_id").over(w).alias("fv"), F.round(F.sum("value").over(w.rowsBetween(-2, 0)), 4).alias("s3"),
    )


@query("select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) as n from events")
def range_window_events(spark, d):
    e = table(spark, d, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-86_400_000_000, 0)).alias("n"))


@query(f"with pool as ({sql.POOLS['basket_name']}) select entity, count(*) as n from pool group by entity order by n desc, entity limit 50")
def topk_entities(spark, d):
    return names(spark, d)[0].groupBy("entity").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "entity").limit(50)


@query("""with a as (select distinct l_partkey as k from lineitem where l_quantity > 40), b as (select distinct l_partkey as k from lineitem where l_discount < 0.01)
    select (select count(*) from (select k from a union select k from b)) as either, (select count(*) from (select k from a intersect select k from b)) as both, (select count(*) from (select k from a except select k from b)) as only_a""")  # fmt: skip
def set_operations(spark, d):
    lines = table(spark, d, "lineitem")
    a, b = lines.filter("l_quantity > 40").select(F.col("l_partkey").alias("k")), lines.filter("l_discount < 0.01").select(F.col("l_partkey").alias("k"))
    count = lambda df, n: df.agg(F.count("*").alias(n))
    return count(a.union(b).distinct(), "either").crossJoin(count(a.intersect(b), "both")).crossJoin(count(a.subtract(b), "only_a"))


@query(f"select doc_id from documents where {sql.draw('42', 'doc_id')} < 0.25")
def keyed_sample(spark, d):
    return ops.keyed_sample(table(spark, d, "documents"), "doc_id", 0.25).select("doc_id")


@query(f"select source, doc_id from documents qualify row_number() over (partition by source order by {sql.draw('42', 'doc_id')}, doc_id) <= 3")
def keyed_sample_by_source(spark, d):
    return ops.keyed_sample_by(table(spark, d, "documents").select("source", "doc_id"), "source", "doc_id", 3).select("source", "doc_id")


@query("""select p_partkey, upper(p_name) as u, translate(p_name, 'aeiou', 'AEIOU') as t, regexp_replace(p_type, '[A-Z]+ ', '', 'g') as r, split_part(p_name, ' ', 1) as f, instr(p_name, 'e') as i, substr(p_name, 2, 3) as s,
    concat_ws('/', p_brand, p_type) as c, levenshtein(p_name, p_type) as lev, length(p_name) as len, md5(p_name) as h from part""")  # fmt: skip
def strings_part(spark, d):
    return table(spark, d, "part").select(
        "p_partkey", F.upper("p_name").alias("u"), F.translate("p_name", "aeiou", "AEIOU").alias("t"), F.regexp_replace("p_type", "[A-Z]+ ", "").alias("r"), F.substring_index("p_name", " ", 1).alias("f"), F.instr("p_name", "e").cast("long").alias("i"),
        F.substring("p_name", 2, 3).alias("s"), F.concat_ws("/", "p_brand", "p_type").alias("c"), F.levenshtein("p_name", "p_type").cast("long").alias("lev"), F.length("p_name").cast("long").alias("len"), F.md5("p_name").alias("h"),
    )


@query("select cast(date_trunc('month', o_orderdate) as date) as m, count(*) as n, min(datediff('day', o_orderdate, o_orderdate + interval 45 day)) as d, max(extract(dow from o_orderdate)) as dow from orders group by 1")
def dates_orders(spark, d):
    day = F.to_date("o_orderdate")
    return table(spark, d, "orders").groupBy(F.to_date(F.date_trunc("month", "o_orderdate")).alias("m")).agg(F.count("*").alias("n"), F.min(F.datediff(F.date_add(day, 45), day)).cast("long").alias("d"), F.max(F.dayofweek("o_orderdate") - 1).cast("long").alias("dow"))


@query("""select vec_id, len(embedding) as n, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 5) as sq, round(list_max(embedding)::double, 5) as top, len(list_filter(embedding, lambda x: x > 0)) as pos,
    len(list_intersect(range(1, 6), [3, 4, 9])) as both from embeddings""")  # fmt: skip
def arrays_embeddings(spark, d):
    v = F.col("embedding")
    return table(spark, d, "embeddings").select(
        "vec_id", F.size(v).cast("long").alias("n"), F.round(F.aggregate(F.transform(v, lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x), 5).alias("sq"), F.round(F.array_max(v).cast("double"), 5).alias("top"),
        F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("pos"), F.size(F.array_intersect(F.sequence(F.lit(1), F.lit(5)), F.array(F.lit(3), F.lit(4), F.lit(9)))).cast("long").alias("both"),
    )


@query("select lang, array_to_string(list_sort(list(source || '=' || n)), ',') as counts from (select lang, source, count(*) as n from documents group by all) group by lang")
def maps_documents(spark, d):
    rows = table(spark, d, "documents").groupBy("lang", "source").agg(F.count("*").alias("n")).groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    text = F.transform(F.map_keys("m"), lambda k: F.concat(k, F.lit("="), F.element_at("m", k).cast("string")))
    return rows.select("lang", F.array_join(F.array_sort(text), ",").alias("counts"))


@query("select o_orderkey, '{\"k\":' || o_custkey || ',\"s\":\"' || o_orderstatus || '\"}' as j, o_custkey as back from orders")
def json_orders(spark, d):
    rows = table(spark, d, "orders").select("o_orderkey", F.to_json(F.struct(F.col("o_custkey").alias("k"), F.col("o_orderstatus").alias("s"))).alias("j"))
    return rows.withColumn("back", F.get_json_object("j", "$.k").cast("long"))


@query("""select query_id, vec_id, score, "rank" from (select q.vec_id as query_id, e.vec_id, round(list_cosine_similarity(q.embedding::double[], e.embedding::double[]), 6) as score, row_number() over (partition by q.vec_id order by round(list_cosine_similarity(q.embedding::double[], e.embedding::double[]), 6) desc, e.vec_id) as "rank"
    from embeddings q join embeddings e on q.vec_id <> e.vec_id where q.vec_id % 100 = 0) where "rank" <= 5""")  # fmt: skip
def brute_neighbors(spark, d):
    rows = table(spark, d, "embeddings").select("vec_id", "embedding")
    return ops.brute_neighbors(rows.filter("vec_id % 100 = 0"), rows, 5)


@query("select label, i - 1 as dim, round(avg(embedding[i]::double), 6) as mean from (select label, embedding, unnest(range(1, len(embedding) + 1)) as i from embeddings) group by all")
def label_centroids(spark, d):
    return ops.centroids(table(spark, d, "embeddings")).select("label", "dim", r6("mean").alias("mean"))


@query("""with w as (select doc_id, list_filter(string_split_regex(lower(text), '\\s+'), lambda w: w <> '') as t from documents), g as (select distinct doc_id, array_to_string(t[i : i + 4], ' ') as s from (select doc_id, t, unnest(range(1, greatest(len(t) - 4, 1) + 1)) as i from w where len(t) > 0)),
    n as (select doc_id, count(*) as n, md5(string_agg(s, '|' order by s)) as k from g group by doc_id), r as (select min(doc_id) as doc_id, any_value(n) as n from n group by k)
    select x.doc_id as a, y.doc_id as b, round(count(*) / (any_value(rx.n) + any_value(ry.n) - count(*)), 6) as jaccard from g x join g y on x.s = y.s and x.doc_id < y.doc_id join r rx on rx.doc_id = x.doc_id join r ry on ry.doc_id = y.doc_id group by x.doc_id, y.doc_id having count(*) / (any_value(rx.n) + any_value(ry.n) - count(*)) >= 0.8""")  # fmt: skip
def shingle_pairs(spark, d):
    return ops.shingle_jaccard(table(spark, d, "documents"), 0.8).select("a", "b", r6("jaccard").alias("jaccard"))


@query("""with w as (select doc_id, list_filter(string_split_regex(lower(text), '\\s+'), lambda w: w <> '') as t from documents), g as (select distinct doc_id, array_to_string(t[i : i + 4], ' ') as s from (select doc_id, t, unnest(range(1, greatest(len(t) - 4, 1) + 1)) as i from w where len(t) > 0)),
    n as (select doc_id, md5(string_agg(s, '|' order by s)) as k from g group by doc_id) select doc_id, coalesce(min(doc_id) over (partition by k), doc_id) as representative from n union all select doc_id, doc_id from w where coalesce(len(t), 0) = 0""")  # fmt: skip
def shingle_members(spark, d):
    """Membership beside `shingle_pairs`, whose pairs are between representatives."""
    return ops.shingle_members(table(spark, d, "documents"))


@query("select doc_id, regexp_replace(regexp_replace(text, '[a-zA-Z0-9._]+@[a-zA-Z0-9.]+', '<mail>', 'g'), '[0-9]{7,}', '<digits>', 'g') as masked from documents")
def mask_personal(spark, d):
    return table(spark, d, "documents").select("doc_id", ops.mask_personal(F.col("text")).alias("masked"))


@query("with l as (select doc_id, unnest(string_split(text, chr(10))) as text from documents) select l.doc_id, count(*) as kept from l where text not in (select text from l where length(text) > 0 group by text having count(distinct doc_id) > 3) group by doc_id")
def repeated_lines(spark, d):
    lines = table(spark, d, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("line", "text"))
    return ops.drop_repeated_lines(lines, 3).groupBy("doc_id").agg(F.count("*").alias("kept"))


@query("with recursive " + sql.recall("basket_name", 1, 20, 4, 3) + """, h(target, entity, hop) as (select target, target, 0 from targets union select h.target, e.dst, h.hop + 1 from h join edges e on e.target = h.target and e.src = h.entity where e.kept and h.hop < 3)
    select target, entity, min(hop) as hop from h group by all""")  # fmt: skip
def hops_from_target(spark, d):
    targets = names(spark, d, 1)[1]
    g = name_graph(spark, d)
    g.edges.join(targets, "target").filter("kept").select("target", "src", "dst").distinct().createOrReplaceTempView("_hop_edges")
    targets.createOrReplaceTempView("_hop_targets")
    return spark.sql("""with recursive h(target, entity, hop) as (select target, target, 0 from _hop_targets union all select h.target, e.dst, h.hop + 1 from h join _hop_edges e on e.target = h.target and e.src = h.entity where h.hop < 3)
        select target, entity, min(hop) as hop from h group by target, entity""")


@query(f"select doc_id, round({sql.draw('42', 'doc_id')}, 9) as u from documents")
def sql_function_draw(spark, d):
    spark.sql("create or replace temporary function draw01(k string) returns double return cast(conv(substring(md5(k), 1, 8), 16, 10) as double) / 4294967296.0")
    table(spark, d, "documents").createOrReplaceTempView("_draw_docs")
    return spark.sql("select doc_id, round(draw01(concat(:seed, '|', doc_id)), 9) as u from _draw_docs", args={"seed": "42"})


@query()
def approx_distinct(spark, d):
    rows = table(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("e"))
    return rows.select(((F.col("a") <= F.col("e") * 1.1) & (F.col("a") >= F.col("e") * 0.9)).alias("close"))


@query("""select 'both' as kind, l_partkey % 50 as k from lineitem where l_quantity < 5 intersect all select 'both', o_custkey % 50 from orders
    union all (select 'only', l_partkey % 50 from lineitem where l_quantity < 5 except all select 'only', o_custkey % 50 from orders)""")
def set_operations_all(spark, d):
    a = table(spark, d, "lineitem").filter("l_quantity < 5").select((F.col("l_partkey") % 50).alias("k"))
    b = table(spark, d, "orders").select((F.col("o_custkey") % 50).alias("k"))
    return a.intersectAll(b).select(F.lit("both").alias("kind"), "k").unionByName(a.exceptAll(b).select(F.lit("only").alias("kind"), "k"))


@query("select 'STRUCT<k: BIGINT>' as schema, cast(count(*) as bigint) as n from events")
def json_schema(spark, d):
    return table(spark, d, "events").agg(F.count("*").alias("n")).select(F.schema_of_json(F.lit('{"k": 1}')).alias("schema"), "n")


@query("select event_type, round(quantile_cont(abs(value - m), 0.5), 6) as mad from (select event_type, value, quantile_cont(value, 0.5) over (partition by event_type) as m from events) group by event_type")
def grouped_pandas(spark, d):
    """A grouped-aggregate pandas function: median absolute deviation (each group in one task; for groups of bounded size)."""
    @F.pandas_udf("double")
    def mad(values: pd.Series) -> float:
        return float((values - values.median()).abs().median())

    return table(spark, d, "events").groupBy("event_type").agg(r6(mad("value")).alias("mad"))


@query("select coalesce(a.k, b.k) as k, coalesce(a.n, 0) as orders, coalesce(b.n, 0) as customers from (select o_custkey % 20 as k, count(*) as n from orders group by all) a full join (select c_custkey % 20 as k, count(*) as n from customer group by all) b on a.k = b.k")
def cogrouped(spark, d):
    """Both sides of a key in one Arrow function."""
    import pyarrow as pa

    def both(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        return pa.table({"k": [key[0].as_py()], "orders": [left.num_rows], "customers": [right.num_rows]})

    a = table(spark, d, "orders").select((F.col("o_custkey") % 20).alias("k")).groupBy("k")
    b = table(spark, d, "customer").select((F.col("c_custkey") % 20).alias("k")).groupBy("k")
    return a.cogroup(b).applyInArrow(both, "k long, orders long, customers long")
