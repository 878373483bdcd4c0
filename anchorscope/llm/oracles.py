"""DuckDB twins of the operators that SQL can express."""

ORACLES: dict[str, str] = {}

# Draw of spark.u01 for a seed and an id.
_DRAW = "(cast('0x' || substr(md5('{seed}|' || coalesce(cast(doc_id as varchar), 'null')), 1, 13) as bigint) + 0.5) / 4503599627370496.0"

ORACLES["op9_warc"] = """
with p as (
    select page_id, coalesce(html, '') as html, sha256(coalesce(html, '')) as payload_digest, strlen(coalesce(html, '')) as payload_bytes from pages
), m as (
    select *, min(page_id) over (partition by payload_digest) as least from p
)
select page_id, payload_bytes, payload_digest,
    case when payload_bytes >= 100 and least < page_id then 'revisit' else 'response' end as record_type,
    case when payload_bytes >= 100 and least < page_id then least end as refers_to
from m
"""

ORACLES["op8_mixing"] = f"""
with d as (
    select doc_id, source, {_DRAW.format(seed=23)} as u, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) as size from documents
), s as (
    select source, sum(size) as source_size, [5.0, 2.0, 1.0][cast((row_number() over (order by source nulls last) - 1) % 3 as int) + 1] as weight from d group by source
), l as (
    select *, 2 * source_size / weight as level, 1.5 * sum(source_size) over ()
        - 2 * coalesce(sum(source_size) over (order by 2 * source_size / weight, source nulls last rows between unbounded preceding and 1 preceding), 0) as rest,
        sum(weight) over (order by 2 * source_size / weight, source nulls last rows between current row and unbounded following) as weights
    from s
), o as (
    select *, level <= rest / weights as is_full from l
), t as (
    select source, source_size, case when is_full then 2.0 * source_size
        else max(case when not is_full then rest / weights end) over () * weight end as target
    from o
), w as (
    select *, case when source_size > 0 then floor(target / source_size + 1e-9) else 0 end as whole from t
), m as (
    select w.*, greatest(0.0, target - whole * source_size) as missing from w
), v as (
    select source, size, sum(size) as w, any_value(missing) as missing from d join m using (source) where size > 0 group by source, size
    union all select null, d.size, sum(d.size), any_value(missing) from d join m on d.source is null and m.source is null where d.size > 0 group by d.size
), e as (
    select source, size, missing - coalesce(sum(w) over (partition by source order by size desc rows between unbounded preceding and 1 preceding), 0) as still,
        sum(cast(size as double) * w) over (partition by source order by size desc rows between current row and unbounded following) as rest
    from v
), f as (
    select *, min(case when still * size >= rest then 1 else 0 end) over (partition by source order by size desc rows between unbounded preceding and current row) = 1 as certain from e
), g as (
    select source, min(case when certain then size end) as least, coalesce(arg_max(still / rest, size) filter (not certain), 0) as c, coalesce(arg_max(still, size) filter (not certain), 0) as still from f group by source
), q as (
    select d.doc_id, d.size, m.source_size, m.target, m.whole, g.still, d.source, d.size > 0 and coalesce(d.size >= g.least, false) as certain,
        case when d.size > 0 and not coalesce(d.size >= g.least, false) and g.c * d.size > 0 and g.c * d.size < 1 then (d.u / (1 - d.u)) / (g.c * d.size / (1 - g.c * d.size)) end as pareto
    from d join m on d.source is not distinct from m.source left join g on d.source is not distinct from g.source
), r as (
    select *, coalesce(sum(case when pareto is not null then size else 0 end) over (partition by source order by pareto nulls last, doc_id rows between unbounded preceding and 1 preceding), 0) as before from q
)
select doc_id, cast(size as bigint) as size, cast(source_size as bigint) as source_size, cast(target as double) as target,
    cast((whole + case when certain or (pareto is not null and before + size / 2.0 <= still) then 1 else 0 end) * size as bigint) as taken
from r
"""

ORACLES["op10_decontamination"] = """
with w as (
    select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') as words from documents
), b as (
    select coalesce(cast(item_id as varchar), 'null') as item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') as words from benchmark
), k as (
    select item_id, n, array_to_string(words[i : i + n - 1], ' ') as gram
    from (select item_id, words, least(10, len(words)) as n, unnest(range(1, len(words) - least(10, len(words)) + 2)) as i from b where len(words) > 0)
), g as (
    select doc_id, n, i, array_to_string(words[i : i + n - 1], ' ') as gram
    from (select doc_id, words, n, unnest(range(1, len(words) - n + 2)) as i from w, (select distinct n from k) where len(words) >= n)
), h as (
    select g.doc_id, g.i, g.n, k.item_id from g join k on g.n = k.n and g.gram = k.gram
), p as (
    select doc_id, count(distinct j) as n_hit from (select doc_id, unnest(range(i, i + n)) as j from h) group by doc_id
), q as (
    select doc_id, count(*) as n_items, string_agg(item_id, ',' order by item_id) as items from (select distinct doc_id, item_id from h) group by doc_id
)
select w.doc_id, len(w.words) as n_words, coalesce(p.n_hit, 0) as n_hit, coalesce(q.n_items, 0) as n_items, sha256(coalesce(q.items, '')) as items_sha256, p.n_hit is not null as contaminated
from w left join p on w.doc_id = p.doc_id left join q on w.doc_id = q.doc_id
"""

# A table of CRC-32 by its polynomial, and its use byte by byte.
ORACLES["op6_sharding"] = f"""
with table_ as (
    select list(list_reduce([cast(i as bigint), 0, 0, 0, 0, 0, 0, 0, 0], lambda c, z: case when c & 1 = 1 then xor(c >> 1, 3988292384) else c >> 1 end) order by i) as t from range(256) r(i)
), d as (
    select doc_id, source, coalesce(text, '') as text, {_DRAW.format(seed=17)} as u, coalesce('=' || source, 'null') as key from documents
), h as (
    select *, hex(encode(text)) as x from d
), c as (
    select *, xor(list_reduce(list_prepend(cast(4294967295 as bigint), list_transform(range(cast(len(x) / 2 as bigint)), lambda i: cast('0x' || substr(x, 2 * i + 1, 2) as bigint))),
        lambda c, b: xor(c >> 8, t[xor(c & 255, b) + 1])), 4294967295) as crc
    from h, table_
), f as (
    select *, (row_number() over (partition by key order by u, cast(doc_id as varchar)) - 1 + 0.5) / count(*) over (partition by key) as f from c
), a as (
    select *, row_number() over (order by f, key) - 1 as place, count(*) over () as total from f
), s as (
    select *, ((place + 1) * 40 - 1) // total as shard from a
)
select doc_id, cast(strlen(text) + 16 as bigint) as size, crc as text_crc32, 'rows' as law, cast(shard as int) as shard, cast(place - (shard * total) // 40 as bigint) as slot, cast(null as int) as grown_shard
from s
"""
