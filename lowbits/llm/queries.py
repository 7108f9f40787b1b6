"""The registered queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, line_dedup, media_ts, mixing, ngram_join, secret_scan, substring_dedup, suffix_dedup, toxicity, url_lists
from .engine import table


def op1_transport_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_ts.digests(media_ts.encode(table(spark, sf_dir, "documents")))


def op2_temperature_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixing.mix(table(spark, sf_dir, "documents"))
    return out.withColumns({"block": out.block.cast("long"), "pass": out["pass"].cast("long"), "weight": F.round("weight", 6), "exponent": F.round("exponent", 6)})


def op3_line_deletion_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.line_report(table(spark, sf_dir, "documents")).withColumn("removed", F.array_join("removed", ","))


def op4_temporal_url_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    out = url_lists.evaluate(url_lists.dated_captures(pages), url_lists.derived_feed(pages))
    return out.withColumns({c: out[c].cast("string") for c in ("fetched", "listed_since")})


def op5_suffix_cover(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.report(table(spark, sf_dir, "documents"))


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.report(decontam.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))


def op7_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.classes(table(spark, sf_dir, "documents"))


def op8_unit_hashing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring_dedup.dedup(table(spark, sf_dir, "documents"), substring_dedup.BOTH, with_kept=False)
    return out.withColumn("removed", F.array_join(F.transform("removed", lambda x: F.concat_ws(":", x["start"].cast("string"), x["end"].cast("string"))), ","))


def op9_toxicity_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def op10_secret_ownership(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_transport_stream, op2_temperature_mixing, op3_line_deletion_join, op4_temporal_url_lists, op5_suffix_cover, op6_decontamination, op7_ngram_jaccard, op8_unit_hashing, op9_toxicity_chain, op10_secret_ownership)
}

_M = lambda text: f"cast('0x' || substr(md5({text}), 1, 7) as bigint)"
_UPPER, _LOWER, _WORD = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ'", "'abcdefghijklmnopqrstuvwxyz'", r"'[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'"
_ASSIGN, _ACCESS, _HEX = (x.replace("'", "''") for x in (secret_scan.ASSIGN, secret_scan.ACCESS, secret_scan.HEX.rstrip("+")))
_SPLIT = lambda kind, p, g: f"'{kind}' as kind, unnest(regexp_split_to_array(text, '{p}')) as gap, unnest(regexp_extract_all(text, '{p}', 0)) as hit, unnest(regexp_extract_all(text, '{p}', {g})) as v, unnest(range(1, len(regexp_extract_all(text, '{p}', 0)) + 2)) as i"
_H = lambda text: f"cast('0x' || substr(md5({text}), 1, 15) as bigint)"
_SCHEME = "^[A-Za-z][A-Za-z0-9+.-]*://"
ORACLES: dict[str, str] = {
    "op4_temporal_url_lists": f"""
    with c as (select page_id, lower(coalesce(regexp_extract(url, '{_SCHEME}([^/?#:]+)', 1), '')) as host, coalesce(regexp_extract(url, '{_SCHEME}[^/?#]+/([^/?#]+)', 1), '') as segment,
                      cast(date '2024-01-01' + cast({_M("'fetch:' || page_id")} % 366 as integer) as date) as fetched from pages),
    l as (select *, string_split(host, '.') as labels from c),
    k as (select page_id, 'host' as kind, host as key from l where host <> ''
          union all select page_id, 'domain', array_to_string(labels[i:], '.') from (select page_id, labels, unnest(range(1, greatest(len(labels) - 1, 1) + 1)) as i from l where host <> '')
          union all select page_id, 'prefix', host || '/' || segment from l where host <> '' and segment <> ''),
    s as (select kind, key, m, cast(date '2024-01-01' + cast(m % 366 as integer) as date) as start from (select distinct kind, key, {_M("kind || ':' || key")} as m from k) where m % 3 = 0),
    e as (select kind, key, m, start as day, 1 as opened from s union all select kind, key, m, start + cast(20 + m % 60 as integer), 0 from s where m % 4 <> 1 union all select kind, key, m, start + 120, 1 from s where m % 5 = 0),
    w as (select *, coalesce(lag(opened) over (partition by kind, key order by day, opened desc), 0) as was from e),
    v as (select *, lead(day) over (partition by kind, key order by day, opened desc) as to_day from w where opened <> was),
    i as (select kind, key, case when m % 2 = 0 then 'adult' else 'malware' end as category, day as from_day, to_day from v where opened = 1 and (to_day is null or to_day > day)),
    h as (select k.page_id, k.kind || ':' || k.key || ':' || category as rule, from_day from k join i on k.kind = i.kind and k.key = i.key join c on c.page_id = k.page_id where from_day <= fetched and (to_day is null or fetched < to_day)),
    g as (select page_id, count(*) as n, string_agg(rule, ',' order by rule) as rules, min(from_day) as since from h group by page_id)
    select c.page_id, host, cast(fetched as varchar) as fetched, n is not null as blocked, coalesce(n, 0) as n_rules, coalesce(rules, '') as rules, cast(since as varchar) as listed_since from c left join g on g.page_id = c.page_id""",
    "op6_decontamination": f"""
    with t as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), {_UPPER}, {_LOWER}), {_WORD}) as t from documents),
    b as (select item_id, regexp_extract_all(translate(coalesce(text, ''), {_UPPER}, {_LOWER}), {_WORD}) as t from benchmark),
    p as (select distinct item_id, least(len(t), 10) as n, unnest([array_to_string(t[i:i+least(len(t), 10)-1], ' ') for i in range(1, greatest(len(t)-9, 1)+1)]) as w from b where len(t) > 0),
    d as (select doc_id, n, unnest([array_to_string(t[i:i+n-1], ' ') for i in range(1, len(t)-n+2)]) as w, unnest(range(1, len(t)-n+2)) as i from t, (select distinct n from p) where len(t) >= n),
    h as (select distinct doc_id, i, d.n, item_id from d join p using (n, w)),
    c as (select doc_id, count(*) as n_hit from (select distinct doc_id, unnest(range(i, i+n)) from h) group by doc_id),
    g as (select doc_id, count(*) as n_items, string_agg(x, ',' order by x) as items from (select distinct doc_id, cast(item_id as varchar) as x from h) group by doc_id)
    select t.doc_id, cast(len(t) as bigint) as n_words, coalesce(n_hit, 0) as n_hit, coalesce(n_items, 0) as n_items, sha256(coalesce(items, '')) as items_sha256, n_hit is not null as contaminated
    from t left join c on c.doc_id = t.doc_id left join g on g.doc_id = t.doc_id""",
    "op10_secret_ownership": f"""
    with d as (select doc_id, source as owner, coalesce(source, '') || '/' || coalesce(lang, '') as repo, coalesce(text, '') as text from documents),
    m as (select doc_id, owner, repo, {_SPLIT('assign', _ASSIGN, 2)} from d union all select doc_id, owner, repo, {_SPLIT('access', _ACCESS, 0)} from d union all select doc_id, owner, repo, {_SPLIT('hex', _HEX, 0)} from d),
    e as (select *, sum(length(gap) + length(hit)) over (partition by doc_id, kind order by i) as stop from m where hit is not null),
    s as (select *, stop - length(hit) as start, sha256(v) as digest from e where kind <> 'assign' or length(v) >= 12),
    o as (select digest, count(distinct owner) + max(case when owner is null then 1 else 0 end) as owners, count(distinct coalesce(owner, chr(0)) || repo) as repos from s group by digest),
    q as (select doc_id, count(*) filter (owners >= 3 or repos >= 5) as n_copied, count(*) filter (not (owners >= 3 or repos >= 5)) as n_live, max(owners) as most_owners from (select distinct doc_id, digest from s) join o using (digest) group by doc_id),
    a as (select doc_id, count(*) filter (kind = 'assign') as n_assign, count(*) filter (kind = 'access') as n_access, count(*) filter (kind = 'hex') as n_hex,
                 string_agg(kind || ':' || start || ':' || stop, ',' order by start, case kind when 'assign' then 0 when 'access' then 1 else 2 end) as spans from s group by doc_id)
    select d.doc_id, coalesce(n_assign, 0) as n_assign, coalesce(n_access, 0) as n_access, coalesce(n_hex, 0) as n_hex, sha256(coalesce(spans, '')) as base_sha256, coalesce(spans, '') as spans,
           coalesce(n_live, 0) as n_live, coalesce(n_copied, 0) as n_copied, cast(coalesce(most_owners, 0) as bigint) as most_owners
    from d left join a on a.doc_id = d.doc_id left join q on q.doc_id = d.doc_id""",
    "op3_line_deletion_join": f"""
    with x as (select doc_id, unnest(string_split(text, chr(10))) as l, unnest(range(0, len(string_split(text, chr(10))))) as i from documents where text is not null),
    l as (select doc_id, i, regexp_extract_all(translate(l, {_UPPER}, {_LOWER}), {_WORD}) as w, doc_id * 10000000 + i as place from x),
    f as materialized (select array_to_string(w, ' ') as form, any_value(w) as w, any_value(len(w)) as n, min(place) as first from l where len(w) > 0 group by 1),
    v as materialized (select form, first, p, array_to_string(list_concat(w[:p-1], w[p+1:]), ' ') as v from (select *, unnest(range(1, n + 1)) as p from f where n >= 8)),
    gone as (select form from (select form, first, min(first) over (partition by v, p) as least from v) where first > least
             union select v.form from v join f on f.form = v.v and f.n >= 8 where f.first < v.first
             union select f.form from v join f on f.form = v.v and f.n >= 8 where v.first < f.first),
    r as (select l.doc_id, l.i from l join f on f.form = array_to_string(l.w, ' ') and len(l.w) > 0 where l.place > f.first or f.form in (select form from gone)),
    g as (select doc_id, count(*) as n, string_agg(cast(i as varchar), ',' order by i) as removed from r group by doc_id)
    select d.doc_id, cast(case when length(text) > 0 then len(string_split(text, chr(10))) else 0 end as bigint) as n_lines, coalesce(n, 0) as n_removed, coalesce(removed, '') as removed
    from documents d left join g on g.doc_id = d.doc_id""",
    "op8_unit_hashing": f"""
    with t as (select doc_id, list_filter(string_split(replace(coalesce(text, ''), chr(10), chr(10) || chr(1)), chr(1)), lambda y: y <> '') as u from documents),
    z as (select doc_id, unnest(u) as l, unnest(range(0, len(u))) as li from t),
    y as (select *, regexp_extract_all(translate(l, {_UPPER}, {_LOWER}), {_WORD}) as lw from z),
    r as (select doc_id, li, list_filter(string_split(regexp_replace(l, '([.!?]) ', '\\1 ' || chr(1), 'g'), chr(1)), lambda y: y <> '') as p,
                 len(lw) >= 8 and doc_id * 10000000 + li > min(doc_id * 10000000 + li) over (partition by len(lw) >= 8, array_to_string(lw, ' ')) as line_gone,
                 len(lw) >= 8 and count(*) over (partition by len(lw) >= 8, array_to_string(lw, ' ')) > 1 as line_many from y),
    f as (select doc_id, count(*) filter (line_many) as n_lines from r group by doc_id),
    v as (select doc_id, li, line_gone, unnest(p) as s, unnest(range(0, len(p))) as si from r),
    x as (select doc_id, line_gone, s, row_number() over (partition by doc_id order by li, si) - 1 as i from v),
    w as (select *, regexp_extract_all(translate(s, {_UPPER}, {_LOWER}), {_WORD}) as w, sum(strlen(s)) over (partition by doc_id order by i) as stop from x),
    k as (select doc_id, i, s, stop, line_gone or (len(w) >= 8 and doc_id * 10000000 + i > min(doc_id * 10000000 + i) over (partition by len(w) >= 8, array_to_string(w, ' '))) as gone,
                 len(w) >= 8 and count(*) over (partition by len(w) >= 8, array_to_string(w, ' ')) > 1 as many from w),
    n as (select *, i - row_number() over (partition by doc_id order by i) as island from k where gone),
    m as (select doc_id, island, min(stop - strlen(s)) as a, max(stop) as b from n group by 1, 2),
    g as (select doc_id, string_agg(a || ':' || b, ',' order by a) as removed from m group by doc_id),
    q as (select doc_id, count(*) as n_units, count(*) filter (gone) as n_removed, count(*) filter (many) as n_many, sha256(coalesce(string_agg(s, '' order by i) filter (not gone), '')) as kept from k group by doc_id)
    select t.doc_id, coalesce(n_units, 0) as n_units, coalesce(n_removed, 0) as n_removed, coalesce(n_many, 0) + coalesce(n_lines, 0) as n_repeated, coalesce(removed, '') as removed, coalesce(kept, sha256('')) as kept_sha256
    from t left join q on q.doc_id = t.doc_id left join g on g.doc_id = t.doc_id left join f on f.doc_id = t.doc_id""",
    # the repetition limit does not bind wherever the entropy target keeps sources under it, so it has no part here
    "op2_temperature_mixing": f"""
    with recursive d as (select doc_id, source, cast(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) as bigint) as n_tokens, {_H("'7:' || doc_id")} % {mixing.BLOCKS} as block from documents),
    s as materialized (select source, cast(sum(n_tokens) as bigint) as tokens, cast(sum(sum(n_tokens)) over () as double) as total from d group by source),
    b as (select 0 as step, cast(0 as double) as lo, cast(1 as double) as hi
          union all select step + 1, case when e >= goal then mid else lo end, case when e >= goal then hi else mid end from (
            select step, lo, hi, (lo + hi) / 2 as mid, (select ln(sum(power(tokens / total, (lo + hi) / 2))) - sum(power(tokens / total, (lo + hi) / 2) * ln(power(tokens / total, (lo + hi) / 2))) / sum(power(tokens / total, (lo + hi) / 2)) from s where tokens > 0) as e,
                   (select {mixing.TARGET_ENTROPY} * ln(count(*)) from s where tokens > 0) as goal from b where step < {mixing.STEPS})),
    x as (select case when (select -sum(tokens / total * ln(tokens / total)) >= {mixing.TARGET_ENTROPY} * ln(count(*)) from s where tokens > 0) then 1 else (select lo from b where step = {mixing.STEPS}) end as exponent),
    w as (select source, tokens, total, exponent, power(tokens / total, exponent) / sum(power(tokens / total, exponent)) over () as weight from s, x where tokens > 0),
    k as (select d.source, block, cast(sum(n_tokens) as bigint) as size from d group by 1, 2),
    p as (select k.source, block, size, weight, exponent, total * weight as budget, unnest(range(0, cast(ceil(total * weight / tokens) as bigint) + 1)) as pass from k join w on w.source is not distinct from k.source),
    o as (select *, coalesce(sum(size) over (partition by source order by pass, {_H("'7:' || coalesce(source, '') || ':' || pass || ':' || block")}, block rows between unbounded preceding and 1 preceding), 0) as position from p)
    select d.doc_id, d.source, d.n_tokens, d.block, o.pass, cast(o.position as bigint) as position, round(o.weight, 6) as weight, round(o.exponent, 6) as exponent
    from d join o on o.source is not distinct from d.source and o.block = d.block where d.n_tokens > 0 and o.size > 0 and o.position + o.size / cast(2 as double) <= o.budget""",
}
