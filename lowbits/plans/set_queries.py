"""Sets, exact similarity, signatures, estimates and pair strategies on the given tables, with SQL twins."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, coefficients
from ..operators import blocks, estimators, exact, pairs, planes, ranks, sets, signature
from ..sources.io import load, spread, stored

K, W, TOP, R0 = 64, 5, 2633, 0.3
DOMAIN = float(PRIME)
KEY_BITS = 16
WIDE, K_WIDE = 60, 32

# ---- SQL building blocks (DuckDB) -------------------------------------------------------------------


def toks(source: str = "documents", key: str = "doc_id", text: str = "text") -> str:
    return f"(select {key} as set_id, list_filter(string_split(regexp_replace(lower({text}), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g'), ' '), lambda x: x <> '') as t from {source})"


def hashed(s: str = "s", bits: int = 31) -> str:
    return f"cast('0x' || substr(md5({s}), 1, 15) as bigint)" + (f" % {PRIME}" if bits == 31 else f" & {(1 << bits) - 1}")


def shingles_sql(source: str = "documents", key: str = "doc_id", text: str = "text", w: int = W, bits: int = 31) -> str:
    return f"(select distinct set_id, {hashed(bits=bits)} as elem from (select set_id, unnest(list_distinct([array_to_string(t[i:i+{w - 1}], ' ') for i in range(1, len(t)-{w}+2)])) as s from {toks(source, key, text)} where len(t) >= {w}))"


def chars_sql(w: int = 9) -> str:
    letters = "(select doc_id, string_split(regexp_replace(lower(text), '[^\\p{L}\\p{N}]+', ' ', 'g'), '') as t from documents)"
    each = f"(select doc_id as set_id, unnest(t) as ch, generate_subscripts(t, 1) as i, len(t) as n from {letters})"
    runs = f"(select set_id, i, n, string_agg(ch, '') over (partition by set_id order by i rows between current row and {w - 1} following) as s from {each})"
    return f"(select distinct set_id, {hashed()} as elem from {runs} where i <= n - {w} + 1)"


def words_sql() -> str:
    return f"(select distinct set_id as elem, unnest(t) as set_id from {toks()})"


def vocab_sql(top: int = TOP) -> str:
    return f"(select w.set_id, w.elem from {words_sql()} w semi join (select set_id, count(*) n from {words_sql()} group by 1 order by n desc, set_id limit {top}) v using (set_id))"


CUSTOMERS = "(select distinct o_custkey as set_id, l_partkey as elem from lineitem join orders on l_orderkey = o_orderkey)"
PARTS = "(select distinct l_suppkey as set_id, l_partkey as elem from lineitem)"
USERS = "(select distinct event_type || ':' || cast(cast(ts as date) as varchar) as set_id, user_id as elem from events)"
PAGES_TEXT = "regexp_replace(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g')"
PAGES = shingles_sql("pages", "page_id", PAGES_TEXT)


def exact_sql(s: str, r0: float | None = None) -> str:
    cond = f" where cast(a as double)/(f_l+f_r-a) >= {r0}" if r0 is not None else ""
    return f"""with s as {s}, f as (select set_id, count(*) as f from s group by 1),
    p as (select l.set_id as id_l, r.set_id as id_r, count(*) as a from s l join s r on l.elem = r.elem and l.set_id < r.set_id group by 1, 2)
    select id_l, id_r, f_l, f_r, a, cast(a as double)/(f_l+f_r-a) as r from (select id_l, id_r, x.f as f_l, y.f as f_r, a from p join f x on x.set_id = id_l join f y on y.set_id = id_r){cond}"""


def coefficients_sql(k: int = K, seed: int = 0) -> str:
    return "(values " + ", ".join(f"({j}, cast({a} as bigint), cast({c} as bigint))" for j, (a, c) in enumerate(coefficients(k, seed))) + ") co(j, ca, cc)"


def full_sql(s: str, k: int = K, seed: int = 0) -> str:
    return f"(select set_id, j, min((ca*elem+cc) % {PRIME}) as z from {s} s, {coefficients_sql(k, seed)} group by set_id, j)"


def wide_sql(s: str, k: int, seed: int = 0) -> str:
    """Minima under the md5 family."""
    return f"(select set_id, cast(j as integer) as j, min(cast('0x' || substr(md5(concat('{seed}:', j, ':', elem)), 1, 15) as bigint)) as z from {s} s, range({k}) p(j) group by set_id, j)"


def perm_sql(s: str, k: int = K, seed: int = 0) -> str:
    return f"""(select set_id, j, min(rank) as z from {s} s join (select elem, j, row_number() over (partition by j order by md5(concat('{seed}:', j, ':', elem)), elem) - 1 as rank
        from (select distinct elem from {s}) u, range({k}) p(j)) using (elem) group by set_id, j)"""


def bit_(i: int, j: str = "j") -> str:
    return f"bit_or(case when (z >> {i}) & 1 = 0 then cast(0 as bigint) when {j} % 64 = 63 then cast(-9223372036854775807 as bigint) - 1 else cast(1 as bigint) << cast({j} % 64 as integer) end)"


def planes_sql(full: str, b: int) -> str:
    return f"(select set_id, {', '.join(f'{bit_(i)} as p{i}' for i in range(b))} from {full} group by set_id)"


def q_(f: str, d: str, b: int) -> str:
    r, n = f"({f}/cast({d} as double))", float(2**b)
    return f"({r}*power(1-{r},{n}-1)/(1-power(1-{r},{n})))"


def floor_slope_sql(b: int, d: str) -> tuple[str, str]:
    q1, q2 = q_("f_l", d, b), q_("f_r", d, b)
    return f"(({q1}*f_r+{q2}*f_l)/(f_l+f_r))", f"(1-({q1}*f_l+{q2}*f_r)/(f_l+f_r))"


def estimate_sql(s: str, full: str, b: int, d: str, kind: str = "low", r0: float = R0, k: int = K) -> str:
    fl, sl = floor_slope_sql(1 if kind == "fold" else b, d)
    if kind == "fold":
        plane = f"(select set_id, bit_xor(w) as p0 from (select set_id, j // 64 as w_no, {bit_(0)} as w from {full} group by 1, 2) group by set_id)"
        miss, r_hat, err = "bit_count(xor(l.p0, r.p0))", f"(sqrt(greatest(2*e_hat-1, 0))+1-2*{fl})/(2*{sl})", f"case when 2*e_hat > 1 then sqrt(e_hat*(1-e_hat)/(4*{k}*{sl}*{sl}*(2*e_hat-1))) end"
    else:
        plane = planes_sql(full, b)
        miss = "bit_count(" + " | ".join(f"xor(l.p{i}, r.p{i})" for i in range(b)) + ")"
        r_hat = "e_hat" if kind == "full" else f"(e_hat-{fl})/{sl}"
        err = f"sqrt(e_hat*(1-e_hat)/{k})" + ("" if kind == "full" else f"/{sl}")
    return f"""with s as materialized {s}, f as (select set_id, count(*) as f from s group by 1), pl as {plane},
    e as (select l.set_id as id_l, r.set_id as id_r, x.f as f_l, y.f as f_r, cast({k} - {miss} as bigint) as matches, cast({k} - {miss} as double)/{k} as e_hat
          from pl l join pl r on l.set_id < r.set_id join f x on x.set_id = l.set_id join f y on y.set_id = r.set_id),
    h as (select *, {r_hat} as r_hat, {err} as std_err from e),
    p as (select l.set_id as id_l, r.set_id as id_r, count(*) as a from s l join s r on l.elem = r.elem and l.set_id < r.set_id group by 1, 2)
    select h.id_l, h.id_r, f_l, f_r, matches, round(e_hat, 6) as e_hat, round(r_hat, 6) as r_hat, coalesce(round(cast(a as double)/(f_l+f_r-a), 6), 0) as r_exact, round(std_err, 6) as std_err
    from h left join p on p.id_l = h.id_l and p.id_r = h.id_r where r_hat >= {r0}"""


# ---- sets ------------------------------------------------------------------------------------------------


def docs(spark: SparkSession, sf: str) -> DataFrame:
    return spread(load(spark, sf, "documents").select("doc_id", "text"))


def doc_sets(spark, sf) -> DataFrame:
    return sets.shingles(docs(spark, sf), w=W)


def wide_doc_sets(spark, sf, bits: int = WIDE) -> DataFrame:
    return sets.shingles(docs(spark, sf), w=W, bits=bits)


def word_sets(spark, sf, top: int = TOP) -> DataFrame:
    return sets.postings(docs(spark, sf), top_n=top)


def supplier_sets(spark, sf) -> DataFrame:
    return sets.baskets(load(spark, sf, "lineitem"), "l_suppkey", "l_partkey")


def customer_sets(spark, sf) -> DataFrame:
    """Parts each customer ordered."""
    orders = load(spark, sf, "orders").select("o_orderkey", "o_custkey")
    lines = load(spark, sf, "lineitem").select("l_orderkey", "l_partkey")
    return sets.baskets(lines.join(orders, lines.l_orderkey == orders.o_orderkey), "o_custkey", "l_partkey")


def user_sets(spark, sf) -> DataFrame:
    e = load(spark, sf, "events").select(F.concat_ws(":", "event_type", F.to_date("ts").cast("string")).alias("set_key"), "user_id")
    return sets.baskets(e, "set_key", "user_id")


def page_sets(spark, sf) -> DataFrame:
    return sets.shingles(load(spark, sf, "pages").select("page_id", sets.strip_tags("html").alias("text")), "page_id", w=W)


def sets_shingle_count(spark, sf):
    return sets.sizes(doc_sets(spark, sf)).select(F.col("set_id").alias("doc_id"), "f")


def sets_char_shingle_count(spark, sf):
    return sets.sizes(sets.shingles(docs(spark, sf), w=9, unit="char")).select(F.col("set_id").alias("doc_id"), "f")


def sets_postings_df(spark, sf):
    return sets.sizes(sets.postings(docs(spark, sf))).select(F.col("set_id").alias("word"), F.col("f").alias("df"))


def sets_top_vocab(spark, sf):
    return sets_postings_df(spark, sf).orderBy(F.desc("df"), "word").limit(2633)


def sets_density(spark, sf):
    n = docs(spark, sf).agg(F.count("*").alias("d"))
    return sets_top_vocab(spark, sf).crossJoin(n).select("word", F.round(F.col("df") / F.col("d"), 6).alias("density"))


def sets_embedding_top(spark, sf):
    """Set view of vectors: the indices of the 8 greatest coordinates."""
    return sets.top_coordinates(load(spark, sf, "embeddings"), "vec_id", "embedding", 8).groupBy("set_id").agg(F.array_sort(F.collect_list("elem")).alias("e")).select("set_id", F.array_join("e", ",").alias("elems"))


# ---- exact -----------------------------------------------------------------------------------------------


def exact_doc_resemblance(spark, sf):
    return pairs.copies_join(doc_sets(spark, sf), R0)


def exact_word_resemblance(spark, sf):
    return exact.resemblance(sets.postings(docs(spark, sf), top_n=2633), R0).withColumnsRenamed({"id_l": "w1", "id_r": "w2"})


def exact_supplier_resemblance(spark, sf):
    return exact.resemblance(supplier_sets(spark, sf))


def exact_user_day_resemblance(spark, sf):
    return exact.resemblance(user_sets(spark, sf))


def exact_page_resemblance(spark, sf):
    return exact.resemblance(page_sets(spark, sf), R0)


def exact_benchmark_containment(spark, sf):
    b = sets.shingles(load(spark, sf, "benchmark"), "item_id", w=W)
    return exact.containment(b, doc_sets(spark, sf)).where("share >= 0.5")


def exact_conversation_resemblance(spark, sf):
    c = load(spark, sf, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda x: x["text"]), " ").alias("text"))
    return exact.resemblance(sets.shingles(c, "conv_id", w=W))


def exact_distance(spark, sf):
    return exact.distance(exact.all_pairs(supplier_sets(spark, sf))).select("id_l", "id_r", "d")


def exact_distance_triangle(spark, sf):
    return exact.triangle_violations(user_sets(spark, sf)).agg(F.count("*").alias("n_violations"))


# ---- signatures --------------------------------------------------------------------------------------


def sig_full_affine(spark, sf):
    return signature.narrow(signature.build_full(doc_sets(spark, sf), k=16)).select("set_id", F.col("j").cast("int").alias("j"), "z")


def sig_full_narrow(spark, sf):
    """The same minima by exploding permutations: equals the wide form."""
    return signature.build_narrow(doc_sets(spark, sf), k=16).select("set_id", F.col("j").cast("int").alias("j"), "z")


def sig_full_nested(spark, sf):
    """The same minima by the Arrow kernel over array columns, without a shuffle of elements."""
    from ..functions.hashing import to_domain

    t = docs(spark, sf).select("doc_id", sets.tokens("text").alias("t"))
    arr = F.transform(sets.shingle_array(F.col("t"), W), lambda s: to_domain(s))
    n = signature.nested(t.select("doc_id", arr.alias("elems")), "doc_id", "elems", k=16)
    return signature.narrow(n).select("set_id", F.col("j").cast("int").alias("j"), "z")


def sig_full_perm(spark, sf):
    return signature.narrow(signature.build_full(word_sets(spark, sf), "perm", 16)).select(F.col("set_id").alias("word"), F.col("j").cast("int").alias("j"), "z")


def sig_full_wide(spark, sf):
    """60-bit minima of shingles hashed to 60 bits: no chance overlaps at any corpus size."""
    return signature.narrow(signature.build_full(wide_doc_sets(spark, sf), "md5", 16)).select("set_id", F.col("j").cast("int").alias("j"), "z")


def sig_merge(spark, sf):
    """Minima of the union of two halves of the elements, merged, are the minima of the whole."""
    s = doc_sets(spark, sf)
    a, b = (signature.build_full(s.where(F.pmod("elem", F.lit(2)) == i), k=16) for i in (0, 1))
    return signature.narrow(signature.merge(a, b, disjoint=True)).select("set_id", F.col("j").cast("int").alias("j"), "z")


def _planes(spark, sf, b):
    return planes.from_full(signature.build_full(doc_sets(spark, sf), k=K), K, b)


def _sig_planes(b):
    def run(spark, sf):
        return planes.long_form(_planes(spark, sf, b), [f"plane_{i}" for i in range(b)])

    return run


def sig_fold(spark, sf):
    p = planes.from_full(signature.build_full(doc_sets(spark, sf), k=2 * K), 2 * K, 1)
    return planes.long_form(planes.fold(p, K), ["fold"])


# ---- estimates -------------------------------------------------------------------------------------------


def _with_truth(est: DataFrame, s: DataFrame, r0: float = R0) -> DataFrame:
    """Estimates from r0 on next to exact resemblance, counted for these pairs alone."""
    est = stored(est.where(F.col("r_hat") >= r0), "estimates")
    truth = exact.of_pairs(s, est).select("id_l", "id_r", F.round("r", 6).alias("r_exact"))
    return est.join(truth, ["id_l", "id_r"]).select("id_l", "id_r", "f_l", "f_r", "matches", F.round("e_hat", 6).alias("e_hat"), F.round("r_hat", 6).alias("r_hat"), "r_exact", F.round("std_err", 6).alias("std_err"))


def _est_docs(b):
    """Estimates of so many bits and truth, both counted where blocks of documents meet: one bit alone finds a pair in a hundred by chance."""

    def run(spark, sf):
        full = signature.nested(sets.shingle_lists(docs(spark, sf), w=W), "set_id", "elems", K, kept="int")
        return blocks.estimates(planes.from_full(full, K, b, ("elems",)), K, b, R0, DOMAIN, many=True)

    return run


def est_full_docs(spark, sf):
    """Full-width estimates by a prefix join of minima: one document of each set, copies are expanded in the result alone."""
    every = stored(signature.nested(sets.shingle_lists(docs(spark, sf), w=W), "set_id", "elems", K, kept="int"), "sets")
    same = pairs.first_alike(every)
    full = stored(every.select("set_id", "f", "z").join(same.where("set_id = first").select("set_id"), "set_id", "left_semi"), "minima")
    one = every.select("set_id", F.explode("elems").alias("elem"))
    met = stored(pairs.equal_minima(full, K, math.ceil(K * R0 - 1e-9)), "estimates")
    side = lambda s: full.select(F.col("set_id").alias(f"id_{s}"), F.col("f").alias(f"f_{s}"))
    est = met.join(side("l"), "id_l").join(side("r"), "id_r").withColumn("mismatches", K - F.col("a"))
    near = stored(_with_truth(estimators.r_full(est, K), one), "near")
    return pairs.expanded(same, full.select("set_id", "f"), near, {"matches": F.lit(K).cast("long"), "e_hat": F.lit(1.0), "r_hat": F.lit(1.0), "r_exact": F.lit(1.0), "std_err": F.lit(0.0)})


def _universe(s: DataFrame) -> int:
    """Elements that occur: the range of the permutations of word sets."""
    return s.select("elem").distinct().count()


def _words(spark, sf, k: int, b: int) -> tuple[DataFrame, DataFrame, int]:
    """The word sets, their planes and their universe."""
    s = stored(word_sets(spark, sf), "words")
    return s, planes.from_full(signature.build_full(s, "perm", k), k, b), _universe(s)


def _low_words(spark, sf, b) -> tuple[DataFrame, DataFrame]:
    s, sig, d = _words(spark, sf, K, b)
    return s, estimators.r_low(estimators.pair_all(sig, K, b, R0, d), K, b, d).where(F.col("r_hat") >= R0)


def _est_words(b):
    def run(spark, sf):
        s, e = _low_words(spark, sf, b)
        return _with_truth(e, s)

    return run


def est_full_words(spark, sf):
    s, sig, _ = _words(spark, sf, K, 31)
    return _with_truth(estimators.r_full(estimators.pair_all(sig, K, 31, R0), K), s)


def est_full_minima(spark, sf):
    """Full-width estimates by an equi-join on equal minima."""
    s = stored(word_sets(spark, sf), "words")
    return _with_truth(estimators.r_full_minima(signature.build_full(s, "perm", K), K), s)


def est_fold_words(spark, sf):
    s, sig, d = _words(spark, sf, 2 * K, 1)
    return _with_truth(estimators.r_fold(estimators.pair_all(planes.fold(sig, K), K, 1, plane="fold"), K, d), s)


def _est_wide(bits, b=None):
    """Document estimates from minima of so many bits; b: from their lowest b bits alone."""

    def run(spark, sf):
        s = stored(wide_doc_sets(spark, sf, bits), "wide")
        full = signature.build_full(s, "md5", K_WIDE)
        if b is None:
            sig = planes.from_full(full, K_WIDE, bits)
            return _with_truth(estimators.r_full(estimators.pair_all(sig, K_WIDE, bits, R0), K_WIDE), s)
        return _with_truth(pairs.all_pairs(planes.from_full(full, K_WIDE, b), K_WIDE, b, R0, 2.0**WIDE), s)

    return run


def _est_baskets(source, r0):
    """Two-bit estimates of sets in a small universe, by its true permutations; estimates and truth are counted where blocks of sets meet."""

    def run(spark, sf):
        held = exact.members(source(spark, sf))
        s = held.select("set_id", F.explode("elems").alias("elem"))  # rows of a set side by side: its minima are found in one task
        sig = planes.from_full(ranks.minima(s, K, together=True), K, 2).join(held.drop("f"), "set_id")
        return blocks.estimates(sig, K, 2, r0, _universe(s), many=True)

    return run


def est_low_suppliers(spark, sf):
    """Two-bit estimates from 0 on, which every other pair reaches: estimates and truth are counted where blocks of sets meet."""
    s = stored(supplier_sets(spark, sf), "baskets")
    sig = planes.from_full(ranks.minima(s, K), K, 2).join(exact.members(s).drop("f"), "set_id")
    return blocks.estimates(stored(sig, "signatures"), K, 2, 0.0, _universe(s))


def est_low_pages(spark, sf):
    s = stored(page_sets(spark, sf), "pages")
    return _with_truth(pairs.all_pairs(planes.from_full(signature.build_full(s, k=K), K, 2), K, 2, R0, DOMAIN), s)


def est_joint_size(spark, sf):
    e = estimators.joint_size(_low_words(spark, sf, 4)[1])
    return e.select("id_l", "id_r", "f_l", "f_r", F.round("a_hat", 4).alias("a_hat"))


def est_interval(spark, sf):
    e = estimators.with_interval(_low_words(spark, sf, 2)[1])
    return e.select("id_l", "id_r", F.round("low", 6).alias("low"), F.round("high", 6).alias("high"))


# ---- pair strategies ---------------------------------------------------------------------------------------


def _pairs_out(e: DataFrame) -> DataFrame:
    return e.select("id_l", "id_r", "matches", F.round("r_hat", 6).alias("r_hat"))


def pairs_allpairs_b1(spark, sf):
    return _pairs_out(pairs.all_pairs(_planes(spark, sf, 1), K, 1, 0.5, DOMAIN))


def pairs_size_filter(spark, sf):
    return _pairs_out(pairs.size_filtered(stored(_planes(spark, sf, 2), "planes"), K, 2, 0.5, DOMAIN))


def pairs_prefix_filter(spark, sf):
    return pairs.prefix_join(doc_sets(spark, sf), 0.5)


def pairs_banded(spark, sf):
    """Bands of so few rows that a pair at the threshold is met with a probability of 0.9 at least; 16 bits of each sample key a band."""
    rows = pairs.band_rows(0.5, 1e-9, 1e-9, KEY_BITS, K)
    return _pairs_out(pairs.banded(_planes(spark, sf, KEY_BITS), K, 4, rows, 0.5, DOMAIN, KEY_BITS))


def pairs_topk_neighbors(spark, sf):
    top = pairs.top_neighbors(exact.resemblance(supplier_sets(spark, sf)), 3, "r")
    return top.select("id_l", "id_r", F.round("r", 6).alias("r"), F.col("rank").cast("int").alias("rank"))


def dedup_components(spark, sf):
    s = doc_sets(spark, sf)
    c = pairs.duplicate_classes(s, docs(spark, sf).select(F.col("doc_id").alias("set_id")), 0.5)
    return c.select(F.col("set_id").alias("doc_id"), "component_id", "keep")


def dedup_exact_md5(spark, sf):
    """One document of each text is kept: the one with the smallest id."""
    first = docs(spark, sf).groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"))
    return first.select("doc_id", "copies")


QUERIES = {
    f.__name__: f
    for f in (
        sets_shingle_count, sets_char_shingle_count, sets_postings_df, sets_top_vocab, sets_density, sets_embedding_top,
        exact_doc_resemblance, exact_word_resemblance, exact_supplier_resemblance, exact_user_day_resemblance, exact_page_resemblance,
        exact_benchmark_containment, exact_conversation_resemblance, exact_distance, exact_distance_triangle,
        sig_full_affine, sig_full_narrow, sig_full_nested, sig_full_perm, sig_full_wide, sig_merge, sig_fold,
        est_full_docs, est_full_words, est_full_minima, est_fold_words, est_low_pages, est_joint_size, est_interval,
        pairs_allpairs_b1, pairs_size_filter, pairs_prefix_filter, pairs_banded, pairs_topk_neighbors, dedup_components, dedup_exact_md5,
    )
}
QUERIES |= {f"sig_planes_b{b}": _sig_planes(b) for b in (1, 2, 3, 4)}
QUERIES |= {f"est_low_b{b}_docs": _est_docs(b) for b in (1, 2, 3, 4)}
QUERIES |= {"est_full_60bit_docs": _est_wide(60), "est_full_40bit_docs": _est_wide(40), "est_low_b2_wide_docs": _est_wide(60, 2)}
QUERIES |= {"est_low_suppliers": est_low_suppliers, "est_low_customers": _est_baskets(customer_sets, R0), "est_low_user_days": _est_baskets(user_sets, R0)}
QUERIES |= {f"est_low_b{b}_words": _est_words(b) for b in (1, 2, 3, 4)}
_DOCS, _VOC = shingles_sql(), vocab_sql()
_D_WORDS = f"(select count(distinct elem) from {_VOC})"
_NARROW16 = f"select set_id, cast(j as integer) as j, z from {full_sql(_DOCS, 16)}"
_CONV = "(select conv_id, string_agg(text, ' ' order by turn) as text from conversations group by conv_id)"


def _planes_long(b: int) -> str:
    return " union all ".join(f"select set_id, cast({i} as integer) as plane, cast(j // 64 as integer) as word_no, {bit_(i)} as word from {full_sql(_DOCS)} group by set_id, j // 64" for i in range(b))


def _pairs_sql(b: int, r0: float, extra: str = "", stored_planes: int = 0) -> str:
    fl, sl = floor_slope_sql(b, str(PRIME))
    miss = "bit_count(" + " | ".join(f"xor(l.p{i}, r.p{i})" for i in range(b)) + ")"
    return f"""with s as {_DOCS}, f as (select set_id, count(*) as f from s group by 1), pl as {planes_sql(full_sql(_DOCS), max(b, stored_planes))},
    e as (select l.set_id as id_l, r.set_id as id_r, x.f as f_l, y.f as f_r, cast({K} - {miss} as bigint) as matches
          from pl l join pl r on l.set_id < r.set_id join f x on x.set_id = l.set_id join f y on y.set_id = r.set_id {extra})
    select id_l, id_r, matches, round((cast(matches as double)/{K}-{fl})/{sl}, 6) as r_hat from e where (cast(matches as double)/{K}-{fl})/{sl} >= {r0} - 1e-9"""


_ROWS = pairs.band_rows(0.5, 1e-9, 1e-9, KEY_BITS, K)
_APART = "(" + " | ".join(f"xor(l.p{i}, r.p{i})" for i in range(KEY_BITS)) + ")"
_BAND_KEYS = " or ".join(f"(({_APART} >> {_ROWS * t}) & {(1 << _ROWS) - 1}) = 0" for t in range(K // _ROWS))
ORACLES = {
    "sets_shingle_count": f"select set_id as doc_id, count(*) as f from {_DOCS} group by 1",
    "sets_char_shingle_count": f"select set_id as doc_id, count(*) as f from {chars_sql()} group by 1",
    "sets_postings_df": f"select set_id as word, count(*) as df from {words_sql()} group by 1",
    "sets_top_vocab": f"select set_id as word, count(*) as df from {words_sql()} group by 1 order by df desc, word limit 2633",
    "sets_density": f"select word, round(cast(df as double)/(select count(*) from documents), 6) as density from (select set_id as word, count(*) as df from {words_sql()} group by 1 order by df desc, word limit 2633)",
    "sets_embedding_top": "select set_id, array_to_string(list_sort(list(i)), ',') as elems from (select vec_id as set_id, i - 1 as i, row_number() over (partition by vec_id order by x desc, i) as n from (select vec_id, unnest(embedding) as x, generate_subscripts(embedding, 1) as i from embeddings)) where n <= 8 group by set_id",
    "exact_doc_resemblance": exact_sql(_DOCS, R0),
    "exact_word_resemblance": f"select id_l as w1, id_r as w2, f_l, f_r, a, r from ({exact_sql(vocab_sql(2633), R0)})",
    "exact_supplier_resemblance": exact_sql(PARTS),
    "exact_user_day_resemblance": exact_sql(USERS),
    "exact_page_resemblance": exact_sql(PAGES, R0),
    "exact_benchmark_containment": f"with b as {shingles_sql('benchmark', 'item_id')}, f as (select set_id, count(*) as f from b group by 1) select b.set_id as id_s, d.set_id as id_l, count(*) as a, any_value(f.f) as f_s, cast(count(*) as double)/any_value(f.f) as share from b join {_DOCS} d using (elem) join f on f.set_id = b.set_id group by 1, 2 having cast(count(*) as double)/any_value(f.f) >= 0.5",
    "exact_conversation_resemblance": exact_sql(shingles_sql(_CONV, "conv_id")),
    "exact_distance": f"with s as {PARTS}, f as (select set_id, count(*) as f from s group by 1), p as (select l.set_id as x, r.set_id as y, count(*) as a from s l join s r on l.elem = r.elem and l.set_id < r.set_id group by 1, 2) select l.set_id as id_l, r.set_id as id_r, 1 - cast(coalesce(a,0) as double)/(l.f+r.f-coalesce(a,0)) as d from f l join f r on l.set_id < r.set_id left join p on x = l.set_id and y = r.set_id",
    "exact_distance_triangle": f"with s as materialized {USERS}, f as materialized (select set_id, count(*) as f from s group by 1), p as materialized (select l.set_id as x, r.set_id as y, count(*) as a from s l join s r on l.elem = r.elem and l.set_id <> r.set_id group by 1, 2), d as materialized (select l.set_id as x, r.set_id as y, 1 - cast(coalesce(a,0) as double)/(l.f+r.f-coalesce(a,0)) as d from f l join f r on l.set_id <> r.set_id left join p on p.x = l.set_id and p.y = r.set_id) select count(*) as n_violations from d a join d b on b.x = a.y join d c on c.x = a.x and c.y = b.y where c.d > a.d + b.d + 1e-12",
    "sig_full_affine": _NARROW16,
    "sig_full_narrow": _NARROW16,
    "sig_full_nested": _NARROW16,
    "sig_merge": _NARROW16,
    "sig_full_perm": f"select set_id as word, cast(j as integer) as j, z from {perm_sql(_VOC, 16)}",
    "sig_fold": f"select set_id, cast(0 as integer) as plane, cast(0 as integer) as word_no, bit_xor(w) as word from (select set_id, j // 64 as n, {bit_(0)} as w from {full_sql(_DOCS, 2 * K)} group by 1, 2) group by set_id",
    "est_full_docs": estimate_sql(_DOCS, full_sql(_DOCS), 31, str(PRIME), "full"),
    "est_full_words": estimate_sql(_VOC, perm_sql(_VOC), 31, _D_WORDS, "full"),
    "est_full_minima": estimate_sql(_VOC, perm_sql(_VOC), 31, _D_WORDS, "full"),
    "est_fold_words": estimate_sql(_VOC, perm_sql(_VOC, 2 * K), 1, _D_WORDS, "fold"),
    "sig_full_wide": f"select set_id, j, z from {wide_sql(shingles_sql(bits=WIDE), 16)}",
    "est_low_pages": estimate_sql(PAGES, full_sql("s"), 2, str(PRIME)),
    "est_low_customers": estimate_sql(CUSTOMERS, perm_sql("s"), 2, "(select count(distinct elem) from s)"),
    "est_low_user_days": estimate_sql(USERS, perm_sql("s"), 2, "(select count(distinct elem) from s)"),
    "est_low_suppliers": estimate_sql(PARTS, perm_sql(PARTS), 2, f"(select count(distinct elem) from {PARTS})", "low", 0.0),
    "est_joint_size": f"select id_l, id_r, f_l, f_r, round(r/(1+r)*(f_l+f_r), 4) as a_hat from (select *, r_raw as r from ({estimate_sql(_VOC, perm_sql(_VOC), 4, _D_WORDS).replace('round(e_hat, 6) as e_hat', 'r_hat as r_raw')}))",
    "est_interval": f"select id_l, id_r, round(r_raw - 1.96*s_raw, 6) as low, round(r_raw + 1.96*s_raw, 6) as high from ({estimate_sql(_VOC, perm_sql(_VOC), 2, _D_WORDS).replace('round(e_hat, 6) as e_hat', 'r_hat as r_raw, std_err as s_raw')})",
    "pairs_allpairs_b1": _pairs_sql(1, 0.5),
    "pairs_size_filter": _pairs_sql(2, 0.5, "where x.f >= 0.5*y.f and y.f >= 0.5*x.f"),
    "pairs_prefix_filter": exact_sql(_DOCS, 0.5),
    "pairs_banded": _pairs_sql(4, 0.5, f"where {_BAND_KEYS}", KEY_BITS),
    "pairs_topk_neighbors": f"with e as ({exact_sql(PARTS)}), b as (select id_l, id_r, r from e union all select id_r, id_l, r from e) select id_l, id_r, round(r, 6) as r, cast(n as integer) as rank from (select *, row_number() over (partition by id_l order by r desc, id_r) as n from b) where n <= 3",
    "dedup_components": f"with recursive e as (select id_l as a, id_r as b from ({exact_sql(_DOCS, 0.5)})), g as (select a, b from e union select b, a from e), w(node, root) as (select doc_id, doc_id from documents union select g.b, w.root from w join g on g.a = w.node where g.b > w.root) select node as doc_id, min(root) as component_id, node = min(root) as keep from w group by node",
    "dedup_exact_md5": "select min(doc_id) as doc_id, count(*) as copies from documents group by text",
}
ORACLES |= {f"sig_planes_b{b}": _planes_long(b) for b in (1, 2, 3, 4)}
_WIDE_DOCS, _DOCS_40 = shingles_sql(bits=WIDE), shingles_sql(bits=40)
ORACLES |= {"est_low_b2_wide_docs": estimate_sql(_WIDE_DOCS, wide_sql("s", K_WIDE), 2, str(2.0**WIDE), k=K_WIDE).replace(q_("f_l", str(2.0**WIDE), 2), "0.25").replace(q_("f_r", str(2.0**WIDE), 2), "0.25")}
ORACLES |= {f"est_full_{bits}bit_docs": estimate_sql(docs_, wide_sql("s", K_WIDE), bits, str(2.0**WIDE), "full", k=K_WIDE) for bits, docs_ in ((60, _WIDE_DOCS), (40, _DOCS_40))}
ORACLES |= {f"est_low_b{b}_docs": estimate_sql(_DOCS, full_sql(_DOCS), b, str(PRIME)) for b in (1, 2, 3, 4)}
ORACLES |= {f"est_low_b{b}_words": estimate_sql(_VOC, perm_sql(_VOC), b, _D_WORDS) for b in (1, 2, 3, 4)}
