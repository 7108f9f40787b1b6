"""One query per relational operator, around the methods, with SQL twins."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import sqlfuncs
from ..functions.hashing import PRIME, coefficients
from ..operators import blocks, exact, pairs, relational, sets, signature
from ..sources.io import load, round_trip, scratch, stored
from .set_queries import PARTS, _DOCS, docs, exact_sql, supplier_sets, toks, words_sql
from .theory_queries import HALF_UP, bfac_, e_, measured, measured_sql

_PAIRS = f"({exact_sql(PARTS)})"
_EV = "(select event_id, user_id, event_type, ts, value from events)"


def _pairs(spark, sf) -> DataFrame:
    return exact.resemblance(supplier_sets(spark, sf))


def _events(spark, sf) -> DataFrame:
    return load(spark, sf, "events").select("event_id", "user_id", "event_type", "ts", "value")


def scan_project_filter(spark, sf):
    return load(spark, sf, "documents").where(F.col("n_chars").between(500, 2000) & F.col("lang").isin("en", "de")).select("doc_id", "lang", "n_chars")


def csv_json_roundtrip(spark, sf):
    """labels through CSV, JSON and ORC; all three come back equal."""
    df = load(spark, sf, "labels")
    out = None
    for fmt in ("csv", "json", "orc"):
        d = round_trip(df, fmt, scratch(spark, fmt)).withColumn("fmt", F.lit(fmt))
        out = d if out is None else out.unionByName(d)
    return out.select("fmt", F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("long").alias("quality"), F.col("toxic").cast("long").alias("toxic"))


def join_inner_broadcast(spark, sf):
    f = sets.sizes(sets.shingles(docs(spark, sf)))
    return load(spark, sf, "documents").select("doc_id", "lang").join(f, F.col("doc_id") == F.col("set_id")).select("doc_id", "lang", "f")


def join_sortmerge(spark, sf):
    o = load(spark, sf, "orders").select("o_orderkey", "o_custkey").hint("merge")
    j = load(spark, sf, "lineitem").select("l_orderkey", "l_partkey").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return j.select("o_custkey", "l_partkey").distinct().groupBy("o_custkey").agg(F.count("*").alias("f"))


def join_left_outer_zero(spark, sf):
    p = exact.all_pairs(supplier_sets(spark, sf))
    return p.select("id_l", "id_r", "a", F.when(F.col("a") == 0, 0.0).otherwise(F.round("r", 6)).alias("r"))  # most pairs share nothing and need no rounding


def join_full_outer(spark, sf):
    """Pairs above 0.15 next to each set's best partner; either side may be missing."""
    p = _pairs(spark, sf)
    high = p.where("r >= 0.15").select("id_l", "id_r", F.round("r", 6).alias("r"))
    best = p.groupBy("id_l").agg(F.max_by("id_r", F.struct("r", -F.col("id_r"))).alias("id_r")).withColumn("best", F.lit(1))
    return high.join(best, ["id_l", "id_r"], "full_outer").select("id_l", "id_r", "r", F.coalesce("best", F.lit(0)).cast("long").alias("best"))


def _partners(spark, sf):
    """Documents with another one at 0.5 or over: copies by their digest, the rest by a prefix join of one document of each text."""
    return pairs.partners(sets.shingles(docs(spark, sf)), 0.5).withColumnRenamed("set_id", "p")


def join_semi(spark, sf):
    return docs(spark, sf).join(_partners(spark, sf), F.col("doc_id") == F.col("p"), "left_semi").select("doc_id")


def join_anti(spark, sf):
    d = docs(spark, sf).select("doc_id")
    return d.join(_partners(spark, sf), F.col("doc_id") == F.col("p"), "left_anti").join(load(spark, sf, "labels"), "doc_id", "left_anti").select("doc_id")


def join_theta_nlj(spark, sf):
    f = sets.sizes(supplier_sets(spark, sf))
    l, r = f.alias("l"), f.alias("r")
    return l.join(r, (F.col("l.set_id") < F.col("r.set_id")) & (F.col("l.f") > F.col("r.f"))).select(F.col("l.set_id").alias("id_l"), F.col("r.set_id").alias("id_r"), (F.col("l.f") - F.col("r.f")).alias("more"))


def join_range_size(spark, sf):
    return relational.range_size_join(sets.sizes(supplier_sets(spark, sf)), 0.95)


def join_asof(spark, sf):
    """Each event with the last earlier view of the same user."""
    e = _events(spark, sf)
    views = e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view_id"))
    return relational.asof_join(e.select("event_id", "user_id", "ts"), views, ["user_id"], "ts", "view_id", "view_id").select("event_id", "view_id")


def join_interval(spark, sf):
    """Pairs of events of one user within an hour."""
    e = _events(spark, sf).select("event_id", "user_id", "ts")
    j = relational.interval_join(e, e, ["user_id"], "ts", 3600)
    return j.where(F.col("l.event_id") != F.col("r.event_id")).select(F.col("l.event_id").alias("first_id"), F.col("r.event_id").alias("second_id"))


def join_lateral_topk(spark, sf):
    """The three suppliers nearest in size, by a lateral join."""
    f = sets.sizes(supplier_sets(spark, sf))
    f.createOrReplaceTempView("lateral_sizes")
    return spark.sql("select l.set_id as id_l, n.id_r, n.gap from lateral_sizes l, lateral (select r.set_id as id_r, abs(r.f - l.f) as gap from lateral_sizes r where r.set_id <> l.set_id order by gap, id_r limit 3) n")


def agg_distinct(spark, sf):
    p = docs(spark, sf).select("doc_id", F.explode(sets.tokens("text")).alias("w")).join(load(spark, sf, "documents").select("doc_id", "lang"), "doc_id")
    return p.groupBy("lang").agg(F.countDistinct("w").alias("words"), F.count("*").alias("tokens"))


def agg_approx_distinct(spark, sf):
    """Whether sketched word counts stay within five standard errors (of 2 %) of the exact ones.

    The sketch keeps few words as they are and only then goes over to 4096 registers (1.6 % standard error): in registers alone, two
    of a document's first ten words that meet in one are an error of a tenth and more.  Words are distinct before they are counted, so
    no sketch is shuffled for each word."""
    p = docs(spark, sf).select("doc_id", F.explode(F.array_distinct(sets.tokens("text"))).alias("w")).distinct()
    sketched = F.hll_sketch_estimate(F.hll_sketch_agg("w", F.lit(12)))
    return p.groupBy("doc_id").agg(F.count("*").alias("words"), (F.abs(sketched - F.count("*")) <= 0.1 * F.count("*")).alias("close"))


def _bucketed(spark, sf):
    return _pairs(spark, sf).select((F.col("id_l") % 3).alias("g"), F.floor(F.col("r") * 50).cast("long").alias("bucket"))


def agg_rollup(spark, sf):
    return _bucketed(spark, sf).rollup("g", "bucket").agg(F.count("*").alias("n"))


def agg_cube(spark, sf):
    return _bucketed(spark, sf).cube("g", "bucket").agg(F.count("*").alias("n"))


def agg_grouping_sets(spark, sf):
    return _bucketed(spark, sf).groupingSets([[F.col("g")], [F.col("bucket")]], F.col("g"), F.col("bucket")).agg(F.count("*").alias("n"))


def agg_pivot(spark, sf):
    return _bucketed(spark, sf).groupBy("bucket").pivot("g", [0, 1, 2]).agg(F.count(F.lit(1))).select("bucket", *(F.coalesce(F.col(str(i)), F.lit(0)).alias(f"g{i}") for i in range(3)))


def agg_bit_or_xor(spark, sf):
    s = supplier_sets(spark, sf)
    return s.groupBy("set_id").agg(F.bit_or("elem").alias("o"), F.bit_xor("elem").alias("x"), F.bit_and("elem").alias("a"))


def agg_hist_percentile(spark, sf):
    return _pairs(spark, sf).agg(F.count("*").alias("n"), *(F.round(F.percentile("r", F.lit(p)), 6).alias(f"p{int(p * 100)}") for p in (0.1, 0.5, 0.9)))


def win_rank(spark, sf):
    w = Window.partitionBy("id_l").orderBy(F.desc("a"))
    return _pairs(spark, sf).select("id_l", "id_r", F.rank().over(w).cast("long").alias("rank"), F.dense_rank().over(w).cast("long").alias("dense")).where("rank <= 5")


def _by_nation(spark, sf) -> DataFrame:
    """Sizes of the suppliers' sets with their nation: windows without a partition would be one task."""
    return sets.sizes(supplier_sets(spark, sf)).join(load(spark, sf, "supplier").select("s_suppkey", "s_nationkey"), F.col("set_id") == F.col("s_suppkey")).select("set_id", "f", "s_nationkey")


def win_lag_lead(spark, sf):
    w = Window.partitionBy("s_nationkey").orderBy(F.desc("f"), "set_id")
    return _by_nation(spark, sf).select("set_id", "f", (F.col("f") - F.lag("f").over(w)).alias("step"), F.lead("set_id").over(w).alias("next"))


def win_running_k(spark, sf):
    """Matching minima among the first k samples, for every k at once: a running sum over samples, counted in the bits of a pair's equal ones.

    A window over the pairs would shuffle 16 rows for each of them."""
    sig = stored(signature.build_full(supplier_sets(spark, sf), k=16), "minima")
    upto = F.inline(F.array(*(F.struct(F.lit(k).cast("long").alias("k"), F.lit((1 << k) - 1).cast("long").alias("first")) for k in range(1, 17))))
    each = blocks.equal_samples(sig, 16).select("id_l", "id_r", "equal", upto)
    return each.select("id_l", "id_r", "k", F.bit_count(F.col("equal").bitwiseAND(F.col("first"))).cast("long").alias("matches"))


def win_ntile(spark, sf):
    return _by_nation(spark, sf).select("set_id", "f", F.ntile(4).over(Window.partitionBy("s_nationkey").orderBy("f", "set_id")).cast("long").alias("quartile"))


def topk_pairs(spark, sf):
    return _pairs(spark, sf).orderBy(F.desc("r"), "id_l", "id_r").limit(20).select("id_l", "id_r", F.round("r", 6).alias("r"))


def topn_vocab(spark, sf):
    return sets.sizes(sets.postings(docs(spark, sf))).orderBy(F.desc("f"), "set_id").limit(25).select(F.col("set_id").alias("word"), "f")


def _two(spark, sf):
    p = sets.postings(docs(spark, sf))
    return p.where("set_id = 'the'").select("elem"), p.where("set_id = 'that'").select("elem")


def set_union(spark, sf):
    a, b = _two(spark, sf)
    return a.union(b).distinct()


def set_intersect(spark, sf):
    a, b = _two(spark, sf)
    return a.intersect(b)


def set_except(spark, sf):
    a, b = _two(spark, sf)
    return a.exceptAll(b)


def array_setops(spark, sf):
    """Resemblance of the first and last halves of every text's words, by array functions."""
    t = docs(spark, sf).select("doc_id", sets.tokens("text").alias("t")).where("size(t) >= 2")
    t = t.select("doc_id", F.expr("slice(t, 1, int(size(t) / 2))").alias("a"), F.expr("slice(t, int(size(t) / 2) + 1, size(t))").alias("b"))
    i, u = F.size(F.array_intersect("a", "b")), F.size(F.array_union("a", "b"))
    return t.select("doc_id", i.cast("long").alias("both"), u.cast("long").alias("either"), F.size(F.array_except("a", "b")).cast("long").alias("only_a"), F.round(i / u, 6).alias("r"))


def str_normalize(spark, sf):
    t = sets.tokens("text")
    return docs(spark, sf).select("doc_id", F.size(t).cast("long").alias("n"), F.md5(F.array_join(t, " ")).alias("digest"), F.substring("text", 1, 5).alias("head"))


def date_sets(spark, sf):
    o = load(spark, sf, "orders").select("o_orderkey", F.date_format("o_orderdate", "yyyy-MM").alias("month"))
    j = load(spark, sf, "lineitem").select("l_orderkey", "l_partkey").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return sets.sizes(sets.baskets(j, "month", "l_partkey")).select(F.col("set_id").alias("month"), "f")


def array_hof(spark, sf):
    """Shingles by transform and slice; only their count and the least one are returned."""
    t = docs(spark, sf).select("doc_id", sets.tokens("text").alias("t")).where("size(t) >= 3")
    return t.select("doc_id", sets.shingle_array(F.col("t"), 3).alias("s")).select("doc_id", F.size("s").cast("long").alias("n"), F.array_min(F.transform("s", F.md5)).alias("least"))


def map_json(spark, sf):
    """Values of events.props as elements of a set per event type."""
    e = load(spark, sf, "events").select("event_type", F.get_json_object("props", "$.k").alias("k"))
    return sets.sizes(sets.baskets(e, "event_type", "k")).select(F.col("set_id").alias("event_type"), "f")


def math_bits(spark, sf):
    s = supplier_sets(spark, sf)
    x = F.col("elem")
    return s.select("set_id", "elem", F.bit_count(x).cast("long").alias("ones"), F.shiftleft(x, 3).alias("left"), F.shiftright(x, 2).alias("right"), x.bitwiseXOR(F.lit(1023)).alias("flip"), F.round(F.log1p(x.cast("double")), 6).alias("log"))


def sql_functions(spark, sf):
    """The closed forms as SQL functions, over the pairs of user sets counted in events."""
    sqlfuncs.register(spark)
    measured(spark, sf, [1]).createOrReplaceTempView("lowbits_measured")
    return spark.sql(f"select pair, round(residue(r1, 2) + {HALF_UP}, 6) as q, round(match_prob(r, r1, r2, 1) + {HALF_UP}, 6) as e, round(r_low(match_prob(r, r1, r2, 1), r1, r2, 1) + {HALF_UP}, 6) as back, round(storage_factor(r, r1, r2, 2) + {HALF_UP}, 6) as b from lowbits_measured")


def pandas_udf_minhash(spark, sf):
    """Minima by a vectorised Python function over arrays: equal to the native form."""
    co = coefficients(8)

    @F.pandas_udf("array<bigint>")
    def minima(elems: pd.Series) -> pd.Series:
        return elems.map(lambda x: [int(((a * np.asarray(x, np.int64) + c) % PRIME).min()) for a, c in co])

    s = supplier_sets(spark, sf).groupBy("set_id").agg(F.collect_list("elem").alias("e"))  # one supplier's parts
    return s.select("set_id", F.posexplode(minima("e")).alias("j", "z")).select("set_id", F.col("j").cast("long").alias("j"), "z")


def udtf_shingles(spark, sf):
    """Shingles by a table function."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="s string")
    class Shingles:
        def eval(self, words: list, w: int):
            words = words or []
            yield from sorted({(" ".join(words[i : i + w]),) for i in range(len(words) - w + 1)})

    spark.udtf.register("lowbits_shingles", Shingles)
    docs(spark, sf).select("doc_id", sets.tokens("text").alias("t")).createOrReplaceTempView("lowbits_tokens")
    return spark.sql("select doc_id, count(*) as f from lowbits_tokens, lateral lowbits_shingles(t, 5) group by doc_id")


def signature_store(spark, sf):
    """Planes written to a partitioned store and read back, one plane of four."""
    from ..operators import planes
    from ..sources.io import load_signatures, save_signatures

    path = scratch(spark, "store")
    save_signatures(planes.from_full(signature.build_full(supplier_sets(spark, sf)), 64, 4), path)
    return load_signatures(spark, path, 1).select("set_id", "f", F.col("plane_0")[0].alias("word"))


QUERIES = {
    f"rel_{f.__name__}": f
    for f in (
        scan_project_filter, csv_json_roundtrip, join_inner_broadcast, join_sortmerge, join_left_outer_zero, join_full_outer, join_semi, join_anti, join_theta_nlj,
        join_range_size, join_asof, join_interval, join_lateral_topk, agg_distinct, agg_approx_distinct, agg_rollup, agg_cube, agg_grouping_sets, agg_pivot,
        agg_bit_or_xor, agg_hist_percentile, win_rank, win_lag_lead, win_running_k, win_ntile, topk_pairs, topn_vocab, set_union, set_intersect, set_except,
        array_setops, str_normalize, date_sets, array_hof, map_json, math_bits, sql_functions, pandas_udf_minhash, udtf_shingles, signature_store,
    )
}

_SIZES = f"(select set_id, count(*) as f from {PARTS} group by 1)"
_BUCKETS = f"(select id_l % 3 as g, cast(floor(r*50) as bigint) as bucket from {_PAIRS})"
_E05 = f"(select unnest([id_l, id_r]) as p from ({exact_sql(_DOCS, 0.5)}))"
_CO = lambda k: "(values " + ", ".join(f"({j}, cast({a} as bigint), cast({c} as bigint))" for j, (a, c) in enumerate(coefficients(k))) + ") co(j, ca, cc)"
_Z = lambda k: f"(select set_id, j, min((ca*elem+cc) % {PRIME}) as z from {PARTS} s, {_CO(k)} group by 1, 2)"
_Q = lambda r, n: f"(({r})*power(1-({r}),{n}-1)/(1-power(1-({r}),{n})))"
ORACLES = {
    "rel_scan_project_filter": "select doc_id, lang, n_chars from documents where n_chars between 500 and 2000 and lang in ('en', 'de')",
    "rel_csv_json_roundtrip": "select fmt, cast(doc_id as bigint) as doc_id, cast(quality as bigint) as quality, cast(toxic as bigint) as toxic from labels, (values ('csv'), ('json'), ('orc')) t(fmt)",
    "rel_join_inner_broadcast": f"select doc_id, lang, f from documents join (select set_id, count(*) as f from {_DOCS} group by 1) on set_id = doc_id",
    "rel_join_sortmerge": "select o_custkey, count(distinct l_partkey) as f from lineitem join orders on l_orderkey = o_orderkey group by 1",
    "rel_join_left_outer_zero": f"with s as {PARTS}, f as {_SIZES}, p as (select l.set_id as x, r.set_id as y, count(*) as a from s l join s r on l.elem = r.elem and l.set_id < r.set_id group by 1, 2) select l.set_id as id_l, r.set_id as id_r, coalesce(a, 0) as a, round(cast(coalesce(a, 0) as double)/(l.f+r.f-coalesce(a, 0)), 6) as r from f l join f r on l.set_id < r.set_id left join p on x = l.set_id and y = r.set_id",
    "rel_join_full_outer": f"with p as {_PAIRS}, b as (select id_l, id_r from (select *, row_number() over (partition by id_l order by r desc, id_r) as n from p) where n = 1) select coalesce(h.id_l, b.id_l) as id_l, coalesce(h.id_r, b.id_r) as id_r, round(h.r, 6) as r, cast(case when b.id_l is null then 0 else 1 end as bigint) as best from (select * from p where r >= 0.15) h full outer join b on h.id_l = b.id_l and h.id_r = b.id_r",
    "rel_join_semi": f"select doc_id from documents where doc_id in (select p from {_E05})",
    "rel_join_anti": f"select doc_id from documents where doc_id not in (select p from {_E05}) and doc_id not in (select doc_id from labels)",
    "rel_join_theta_nlj": f"select l.set_id as id_l, r.set_id as id_r, l.f - r.f as more from {_SIZES} l join {_SIZES} r on l.set_id < r.set_id and l.f > r.f",
    "rel_join_range_size": f"select l.set_id as id_l, r.set_id as id_r, l.f as f_l, r.f as f_r from {_SIZES} l join {_SIZES} r on l.set_id < r.set_id and l.f >= cast(0.95 as double)*r.f and r.f >= cast(0.95 as double)*l.f",
    "rel_join_asof": "select e.event_id, v.event_id as view_id from events e left join lateral (select event_id from events v where v.event_type = 'view' and v.user_id = e.user_id and v.ts < e.ts order by v.ts desc, v.event_id desc limit 1) v on true",
    "rel_join_interval": "select l.event_id as first_id, r.event_id as second_id from events l join events r on l.user_id = r.user_id and r.ts >= l.ts and r.ts <= l.ts + interval 1 hour and l.event_id <> r.event_id",
    "rel_join_lateral_topk": f"select id_l, id_r, gap from (select l.set_id as id_l, r.set_id as id_r, abs(r.f-l.f) as gap, row_number() over (partition by l.set_id order by abs(r.f-l.f), r.set_id) as n from {_SIZES} l join {_SIZES} r on l.set_id <> r.set_id) where n <= 3",
    "rel_agg_distinct": f"select lang, count(distinct w) as words, count(*) as tokens from (select set_id, unnest(t) as w from {toks()}) join documents on doc_id = set_id group by lang",
    "rel_agg_approx_distinct": f"select set_id as doc_id, count(distinct w) as words, true as close from (select set_id, unnest(t) as w from {toks()}) group by 1",
    "rel_agg_rollup": f"select g, bucket, count(*) as n from {_BUCKETS} group by rollup(g, bucket)",
    "rel_agg_cube": f"select g, bucket, count(*) as n from {_BUCKETS} group by cube(g, bucket)",
    "rel_agg_grouping_sets": f"select g, bucket, count(*) as n from {_BUCKETS} group by grouping sets ((g), (bucket))",
    "rel_agg_pivot": f"select bucket, count(*) filter (g = 0) as g0, count(*) filter (g = 1) as g1, count(*) filter (g = 2) as g2 from {_BUCKETS} group by bucket",
    "rel_agg_bit_or_xor": f"select set_id, bit_or(elem) as o, bit_xor(elem) as x, bit_and(elem) as a from {PARTS} group by 1",
    "rel_agg_hist_percentile": f"select count(*) as n, round(quantile_cont(r, 0.1), 6) as p10, round(quantile_cont(r, 0.5), 6) as p50, round(quantile_cont(r, 0.9), 6) as p90 from {_PAIRS}",
    "rel_win_rank": f"select * from (select id_l, id_r, rank() over w as rank, dense_rank() over w as dense from {_PAIRS} window w as (partition by id_l order by a desc)) where rank <= 5",
    "rel_win_lag_lead": f"select set_id, f, f - lag(f) over w as step, lead(set_id) over w as next from {_SIZES} join supplier on s_suppkey = set_id window w as (partition by s_nationkey order by f desc, set_id)",
    "rel_win_running_k": f"with z as {_Z(16)} select l.set_id as id_l, r.set_id as id_r, cast(l.j + 1 as bigint) as k, cast(sum(case when l.z = r.z then 1 else 0 end) over (partition by l.set_id, r.set_id order by l.j) as bigint) as matches from z l join z r on l.j = r.j and l.set_id < r.set_id",
    "rel_win_ntile": f"select set_id, f, ntile(4) over (partition by s_nationkey order by f, set_id) as quartile from {_SIZES} join supplier on s_suppkey = set_id",
    "rel_topk_pairs": f"select id_l, id_r, round(r, 6) as r from {_PAIRS} p order by p.r desc, id_l, id_r limit 20",
    "rel_topn_vocab": f"select set_id as word, count(*) as f from {words_sql()} group by 1 order by f desc, word limit 25",
    "rel_set_union": f"select distinct elem from {words_sql()} where set_id in ('the', 'that')",
    "rel_set_intersect": f"select elem from {words_sql()} where set_id = 'the' intersect select elem from {words_sql()} where set_id = 'that'",
    "rel_set_except": f"select elem from {words_sql()} where set_id = 'the' except select elem from {words_sql()} where set_id = 'that'",
    "rel_array_setops": f"select set_id as doc_id, cast(len(list_intersect(a, b)) as bigint) as both, cast(len(list_distinct(list_concat(a, b))) as bigint) as either, cast(len(list_filter(list_distinct(a), lambda x: not list_contains(b, x))) as bigint) as only_a, round(len(list_intersect(a, b))/cast(len(list_distinct(list_concat(a, b))) as double), 6) as r from (select set_id, t[1:len(t)//2] as a, t[len(t)//2+1:len(t)] as b from {toks()} where len(t) >= 2)",
    "rel_str_normalize": f"select set_id as doc_id, cast(len(t) as bigint) as n, md5(array_to_string(t, ' ')) as digest, substr(text, 1, 5) as head from {toks()} join documents on doc_id = set_id",
    "rel_date_sets": "select strftime(o_orderdate, '%Y-%m') as month, count(distinct l_partkey) as f from lineitem join orders on l_orderkey = o_orderkey group by 1",
    "rel_array_hof": f"select set_id as doc_id, cast(len(s) as bigint) as n, list_min(list_transform(s, lambda x: md5(x))) as least from (select set_id, list_distinct([array_to_string(t[i:i+2], ' ') for i in range(1, len(t)-1)]) as s from {toks()} where len(t) >= 3)",
    "rel_map_json": "select event_type, count(distinct json_extract_string(props, '$.k')) as f from events group by 1",
    "rel_math_bits": f"select set_id, elem, cast(bit_count(elem) as bigint) as ones, elem << 3 as left, elem >> 2 as right, xor(elem, cast(1023 as bigint)) as flip, round(ln(1 + cast(elem as double)), 6) as log from {PARTS}",
    "rel_sql_functions": f"select pair, round({_Q('r1', 4)} + {HALF_UP}, 6) as q, round({e_('1')} + {HALF_UP}, 6) as e, round(r + {HALF_UP}, 6) as back, round({bfac_('2')} + {HALF_UP}, 6) as b from {measured_sql([1])}",
    "rel_pandas_udf_minhash": f"select set_id, cast(j as bigint) as j, z from {_Z(8)}",
    "rel_udtf_shingles": f"select set_id as doc_id, count(distinct s) as f from (select set_id, unnest([array_to_string(t[i:i+4], ' ') for i in range(1, len(t)-3)]) as s from {toks()} where len(t) >= 5) group by 1",
    "rel_signature_store": f"with z as {_Z(64)} select z.set_id, any_value(f) as f, bit_or(case when z & 1 = 0 then cast(0 as bigint) when j = 63 then cast(-9223372036854775807 as bigint) - 1 else cast(1 as bigint) << cast(j as integer) end) as word from z join {_SIZES} using (set_id) group by 1",
}
