"""Builders of the SQL twins: pools, K unrolled hops, walks in rounds."""

from __future__ import annotations


def draw(*parts: str) -> str:
    text = " || '|' || ".join(f"cast({p} as varchar)" for p in parts)
    return f"(cast('0x' || substr(md5({text}), 1, 8) as bigint) / 4294967296.0)"


STAR = """select cast(l_orderkey as varchar) as order_id, l_orderkey || ':' || l_linenumber || ':' || l_partkey as record_id,
    ['cust:' || o_custkey, 'part:' || l_partkey, 'supp:' || l_suppkey, 'name:' || p_name, 'brand:' || p_brand, 'type:' || p_type, 'snation:' || sn.n_name, 'cnation:' || cn.n_name,
     'sregion:' || sr.r_name, 'cregion:' || cr.r_name, 'priority:' || o_orderpriority] as facts
    from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey join customer on o_custkey = c_custkey
    join nation sn on s_nationkey = sn.n_nationkey join region sr on sn.n_regionkey = sr.r_regionkey join nation cn on c_nationkey = cn.n_nationkey join region cr on cn.n_regionkey = cr.r_regionkey"""

LINES = """select doc_id || ':' || line || case when chunk > 0 then ':' || chunk else '' end as record_id, substr(t, cast(chunk * 2000 + 1 as bigint), 2000) as text
    from (select doc_id, line, t, unnest(range(0, cast(floor((greatest(length(t), 1) - 1) / 2000) as bigint) + 1)) as chunk
        from (select doc_id, generate_subscripts(l, 1) as line, unnest(l) as t from (select doc_id, string_split(text, chr(10)) as l from documents)))"""

WORDS = "list_filter(string_split_regex(lower({0}), '[^a-z]+'), lambda w: w <> '')"

POOLS = {
    "basket_name": "select distinct cast(l_orderkey as varchar) as record_id, p_name as entity from lineitem join part on l_partkey = p_partkey",
    "basket_brand": "select distinct cast(l_orderkey as varchar) as record_id, p_brand as entity from lineitem join part on l_partkey = p_partkey",
    "basket_part": "select distinct cast(l_orderkey as varchar) as record_id, cast(l_partkey as varchar) as entity from lineitem",
    "star_facts": f"select distinct record_id, unnest(facts) as entity from ({STAR})",
    "customer_facts": f"select distinct order_id as record_id, unnest(facts) as entity from ({STAR})",
    "hour_users": "select distinct strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') as record_id, cast(user_id as varchar) as entity from events",
    "doc_words": f"""select record_id, entity from (select distinct record_id, unnest({WORDS.format('text')}) as entity from ({LINES}) where length(text) >= 20)
        where length(entity) >= 6 qualify count(*) over (partition by entity) between 5 and 0.04 * (select count(*) from ({LINES}) where length(text) >= 20)""",
    "dialog_words": f"""select record_id, entity from (select distinct conv_id || ':' || turn as record_id, unnest({WORDS.format('text')}) as entity from conversations where role = 'assistant')
        where length(entity) >= 4 qualify count(*) over (partition by entity) between 3 and 0.35 * (select count(*) from conversations where role = 'assistant')""",
}


def base(pool: str, targets: int, like: str | None = None) -> str:
    where = f"where entity like '{like}'" if like else ""
    return f"pool as materialized ({POOLS[pool]}), targets as (select entity as target from pool {where} group by entity order by count(*) desc, entity limit {targets})"


def respond(front: str, name: str, n: int, conditioning: str = "soft", seed: int = 42) -> str:
    """CTE `name` (target, anchor, iter, record_id) for the frontier CTE `front` (target, anchor)."""
    join = "join" if conditioning == "strict" else "left join"
    has = "" if conditioning == "none" else "(tp.record_id is not null) desc, "
    return f"""{name} as materialized (select f.target, f.anchor, p.record_id, row_number() over (partition by f.target, f.anchor order by {has}{draw(str(seed), 'f.target', 'f.anchor', 'p.record_id')}, p.record_id) as iter
    from {front} f join pool p on p.entity = f.anchor {join} (select distinct target, record_id from pool join targets on entity = target) tp on tp.target = f.target and tp.record_id = p.record_id qualify iter <= {n})"""


def strengths(resp: str, name: str, n: int, hop: int) -> str:
    return f"""{name} as materialized (select r.target, r.anchor as src, p.entity as dst, {hop} as hop, count(*) as c, count(*) / {n}.0 as s
    from {resp} r join pool p on p.record_id = r.record_id where p.entity <> r.anchor and p.entity <> r.target group by all)"""


def recall(pool: str, targets: int, n: int, need: int, k: int, *, like: str | None = None, conditioning: str = "soft", norm: str = "extracted", seed: int = 42, budget: int | None = None) -> str:
    """CTEs pool, targets, edges, reached (target, entity, hop, s), nodes."""
    parts = [base(pool, targets, like), "f0 as (select target, target as anchor, 1.0 as s from targets)", "v0 as (select target, target as entity from targets)"]
    for h in range(k):
        front = f"f{h}"
        if budget is not None:
            spent = "0" if h == 0 else " + ".join(f"(select count(*) from g{j} where g{j}.target = f{h}.target)" for j in range(h))
            parts.append(f"g{h} as materialized (select target, anchor from (select *, row_number() over (partition by target order by s desc, anchor) as pos_ from f{h}) f{h} where pos_ + {spent} <= {budget})")
            front = f"g{h}"
        total = "sum(c) over (partition by target, src)" if norm == "extracted" else f"sum(case when c >= {need} then c end) over (partition by target, src)"
        w = f"c / {total}" if norm == "extracted" else f"case when c >= {need} then c / {total} else 0 end"
        parts += [
            respond(front, f"r{h}", n, conditioning, seed), strengths(f"r{h}", f"c{h}", n, h + 1),
            f"e{h} as materialized (select target, src, dst, hop, c, s, {w} as w, c >= {need} as kept from c{h})",
            f"n{h + 1} as materialized (select target, dst as entity, {h + 1} as hop, max(s) as s from e{h} where kept and (target, dst) not in (select (target, entity) from v{h}) group by target, dst)".replace("(target, dst) not in (select (target, entity) from v" + str(h) + ")", f"not exists (select 1 from v{h} v where v.target = e{h}.target and v.entity = e{h}.dst)"),
            f"f{h + 1} as (select target, entity as anchor, s from n{h + 1})", f"v{h + 1} as (select * from v{h} union all select target, entity from n{h + 1})",
        ]
    parts.append("edges as materialized (" + " union all ".join(f"select * from e{h}" for h in range(k)) + ")")
    parts.append("reached as (" + " union all ".join(f"select * from n{h + 1}" for h in range(k)) + ")")
    parts.append(f"""nodes as materialized (select target, target as entity, 0 as hop, 1.0 as strength, {n} as c from targets union all
        select r.target, r.entity, r.hop, max(e.s), max(e.c) from reached r join edges e on e.target = r.target and e.dst = r.entity where e.kept group by r.target, r.entity, r.hop)""")
    return ",\n".join(parts)


def walk_steps(r: int, l: int, *, role: str = "forget", weighting: str = "strength", starts: str = "select target, target as node from targets", where: str = "kept", seed: int = 42) -> str:  # noqa: E741
    """CTEs ways and steps (target, walk_id, step, node, w) on top of `recall`."""
    c = "c" if weighting == "strength" else "1"
    parts = [
        f"""ways as materialized (select target, src, dst, w, sum({c}) over (partition by target, src order by dst rows between unbounded preceding and current row) - {c} as lo,
        sum({c}) over (partition by target, src order by dst rows between unbounded preceding and current row) as hi, sum({c}) over (partition by target, src) as total from edges where {where})""",
        f"s0 as (select target, walk_id, 0 as step, node, cast(null as double) as w from ({starts}), (select unnest(range({r})) as walk_id))",
    ]
    for i in range(l):
        d = draw(str(seed), "s.target", f"'{role}'", "s.walk_id", f"'{i}'")
        parts.append(f"s{i + 1} as materialized (select s.target, s.walk_id, {i + 1} as step, y.dst as node, y.w from s{i} s join ways y on y.target = s.target and y.src = s.node where floor({d} * y.total) >= y.lo and floor({d} * y.total) < y.hi)")
    parts.append("steps as materialized (" + " union all ".join(f"select * from s{i}" for i in range(l + 1)) + ")")
    parts.append("paths as materialized (select target, walk_id, list(node order by step) as nodes, list(w order by step) filter (step > 0) as weights, avg(w) as quality from steps group by target, walk_id having count(*) > 1)")
    return ",\n".join(parts)
