"""Experiments as queries, with SQL twins where they are deterministic."""

from __future__ import annotations

from ..experiments import workloads as w
from ..functions.hashing import PRIME
from .set_queries import bit_, floor_slope_sql, full_sql, perm_sql, shingles_sql, vocab_sql, words_sql

QUERIES = {
    "exp_table1_data": w.table1_data,
    "exp_bias_mse": w.bias_mse,
    "exp_fold_mse": w.fold_mse,
    "exp_signature_bias": w.signature_bias,
    "exp_pr_words": w.pr_words,
    "exp_pr_docs": w.pr_docs,
    "exp_space_gain": w.space_gain,
}


def pr_sql(s: str, full, domain: str, bs: list[int], full_bits: int, thresholds: list[float], ks=w.CURVE_KS, reps: int = w.CURVE_REPS) -> str:
    """full(k, seed): SQL of (set_id, j, z) over the table s.  Words of planes are columns p{word}_{bit}."""
    n = -(-max(ks) // 64)

    def est(b: int, k: int) -> str:
        apart = [" | ".join(f"xor(l.p{x}_{i}, r.p{x}_{i})" for i in range(b)) for x in range(-(-k // 64))]
        if k % 64:
            apart[-1] = f"({apart[-1]}) & {(1 << k % 64) - 1}"
        miss = " + ".join(f"cast(bit_count({x}) as integer)" for x in apart)
        e = f"(({k} - ({miss}))/cast({k} as double))"
        if b == full_bits:
            return e
        fl, sl = floor_slope_sql(b, domain)
        return f"({e}-{fl})/{sl}"

    grid = [(b, k) for b in [*bs, full_bits] for k in ks]
    cols = ", ".join(f"{est(b, k)} as e{b}_{k}" for b, k in grid)
    words = ", ".join(f"{bit_(i)} filter (j // 64 = {x}) as p{x}_{i}" for x in range(n) for i in range(full_bits))
    counts = ", ".join(f"count(*) filter (r >= {t}) as rel{t_}, " + ", ".join(f"count(*) filter (e{b}_{k} >= {t}) as ret{b}_{k}_{t_}, count(*) filter (r >= {t} and e{b}_{k} >= {t}) as hit{b}_{k}_{t_}" for b, k in grid) for t_, t in enumerate(thresholds))
    named = ", ".join(f"('{'full' if b == full_bits else 'low'}', {32 if b == full_bits else b}, {k}, cast({t} as double), rel{t_}, ret{b}_{k}_{t_}, hit{b}_{k}_{t_})" for b, k in grid for t_, t in enumerate(thresholds))
    each = " union all ".join(
        f"""(with pl as materialized (select set_id, {words} from {full(max(ks), rep)} group by set_id), v as materialized (select pl.*, f from pl join f using (set_id)),
        h as (select l.set_id as a, r.set_id as b, l.f as f_l, r.f as f_r, {cols} from v l join v r on l.set_id < r.set_id),
        m as (select coalesce(cast(n as double)/(f_l+f_r-n), 0) as r, h.* from h left join t using (a, b)),
        c as materialized (select {counts} from m)
        select x.* from c, lateral (values {named}) x(estimator, b, k, r0, n_rel, n_ret, n_hit))"""
        for rep in range(reps)
    )
    ratio = lambda n: f"case when {n} > 0 then n_hit/cast({n} as double) end"
    return f"""with s as materialized {s}, f as (select set_id, count(*) as f from s group by 1),
    t as materialized (select l.set_id as a, r.set_id as b, count(*) as n from s l join s r on l.elem = r.elem and l.set_id < r.set_id group by 1, 2),
    g as ({each})
    select estimator, cast(b as integer) as b, cast(k as integer) as k, r0, cast(sum(n_rel) as bigint) as n_rel, cast(sum(n_ret) as bigint) as n_ret, cast(sum(n_hit) as bigint) as n_hit,
        round(avg({ratio('n_ret')}), 6) as precision, round(avg({ratio('n_rel')}), 6) as recall, round(stddev_pop({ratio('n_ret')}), 6) as precision_sd, round(stddev_pop({ratio('n_rel')}), 6) as recall_sd from g group by all"""


_VOC, _DOCS = vocab_sql(2633), shingles_sql()
_WANTED = ", ".join(f"('{x}', '{y}')" for x, y in w.PAIRS)
_Q1, _Q2 = (f"((cast({f} as double)/d)*(1-cast({f} as double)/d)/(1-power(1-cast({f} as double)/d,2)))" for f in ("f1", "f2"))
_F, _S = f"(({_Q1}*f2+{_Q2}*f1)/(f1+f2))", f"(1-({_Q1}*f1+{_Q2}*f2)/(f1+f2))"
_R = "(cast(a as double)/(f1+f2-a))"
_E = f"({_F}+{_S}*{_R})"


def _gain(b: int) -> str:
    """Residues at 32 or more bits vanish for densities of at least 3 in 1000 only up to (1-r)^(2^32), which is 0."""
    return f"round({b}*{_R}*(1-{_R})/({_E}*(1-{_E})/power({_S},2)), 4)"


def _own_bias() -> str:
    words = ", ".join(f"'{x}'" for x in sorted({y for p in w.PAIRS for y in p}))
    q = lambda f, b: f"(({f}/d)*power(1-{f}/d,{2**b - 1})/(1-power(1-{f}/d,{2**b})))"
    low = lambda b: (f"(({q('f1', b)}*f2+{q('f2', b)}*f1)/(f1+f2))", f"(1-({q('f1', b)}*f1+{q('f2', b)}*f2)/(f1+f2))")
    rows = ["select pair, 'full' as estimator, 32 as b, r, e32 as r_hat, r*(1-r)/k as theory from g"]
    for b in (1, 2, 3):
        f, sl = low(b)
        e = f"({f}+{sl}*r)"
        rows.append(f"select pair, 'low', {b}, r, (e{b}-{f})/{sl}, {e}*(1-{e})/(k*{sl}*{sl}) from g")
    return f"""with w as materialized {words_sql()}, s as materialized (select * from w where set_id in ({words})), u as materialized (select distinct elem from w),
        z as materialized (select set_id, j, min(rank) as z, count(*) as f from s join (select elem, j, row_number() over (partition by j order by md5(concat('0:', j, ':', elem)), elem) - 1 as rank from u, range({w.OWN_K * w.OWN_REPS}) p(j)) using (elem) group by set_id, j),
        p(w1, w2) as (values {_WANTED}),
        t as (select w1, w2, count(y.elem) as a from p join s x on x.set_id = w1 left join s y on y.set_id = w2 and y.elem = x.elem group by 1, 2),
        g as materialized (select w1 || '-' || w2 as pair, cast(x.f as double) as f1, cast(y.f as double) as f2, any_value(cast(a as double)/(x.f+y.f-a)) as r, cast((select count(*) from u) as double) as d, cast({w.OWN_K} as double) as k,
            avg(case when x.z = y.z then 1 else 0 end) as e32, {", ".join(f"avg(case when xor(x.z, y.z) & {2**b - 1} = 0 then 1 else 0 end) as e{b}" for b in (1, 2, 3))}
            from p join z x on x.set_id = w1 join z y on y.set_id = w2 and x.j = y.j join t using (w1, w2) group by w1, w2, x.j // {w.OWN_K}, x.f, y.f),
        e as ({" union all ".join(rows)})
        select pair, estimator, cast(b as integer) as b, cast({w.OWN_K} as integer) as k, count(*) as reps, round(avg(r_hat - r), 6) as bias, round(var_pop(r_hat), 6) as variance, round(avg((r_hat-r)*(r_hat-r)), 6) as mse, round(any_value(theory), 6) as theory from e group by pair, estimator, b"""


ORACLES = {
    "exp_signature_bias": _own_bias(),
    "exp_table1_data": f"""with p as materialized (select * from {words_sql()} where set_id in ({", ".join(f"'{x}'" for x in sorted({y for p in w.PAIRS for y in p}))})), f as materialized (select set_id, count(*) as f from p group by 1), w(w1, w2) as (values {_WANTED}),
        t as (select w1, w2, count(*) as a from w join p x on x.set_id = w1 join p y on y.set_id = w2 and x.elem = y.elem group by 1, 2),
        u as (select w1, w2, x.f as f1, y.f as f2, a, cast((select count(*) from documents) as double) as d from t join f x on x.set_id = w1 join f y on y.set_id = w2)
        select w1, w2, f1, f2, a, round({_R}, 6) as r, round({_F}, 6) as floor, round({_S}, 6) as slope, {_gain(32)} as gain32, {_gain(64)} as gain64 from u""",
    "exp_pr_words": pr_sql(_VOC, lambda k, seed: perm_sql("s", k, seed), "(select count(distinct elem) from s)", [1, 2, 3, 4], 10, w.WORD_THRESHOLDS),
    "exp_pr_docs": pr_sql(_DOCS, lambda k, seed: full_sql("s", k, seed), str(PRIME), [1, 2, 4], 31, w.DOC_THRESHOLDS),
}
