"""Closed forms over parameter grids, as Column expressions, with SQL twins in plain powers."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import theory
from ..operators import planner
from ..sources.io import load

#: Grids and cases.
DENSITIES = [(1e-10, 1e-10), (0.1, 0.1), (0.5, 0.5), (0.9, 0.9), (0.21, 0.1), (0.6, 0.05)]
EQUAL = [1e-10, 0.1, 0.5, 0.9]
BITS = [1, 2, 3, 4, 8, 16, 32, 64]
#: Densities and resemblance of the ten printed word pairs.
PRINTED = [
    ("KONG-HONG", 0.0145, 0.0143, 0.925),
    ("RIGHTS-RESERVED", 0.187, 0.172, 0.877),
    ("OF-AND", 0.570, 0.554, 0.771),
    ("GAMBIA-KIRIBATI", 0.0031, 0.0028, 0.712),
    ("UNITED-STATES", 0.062, 0.061, 0.591),
    ("SAN-FRANCISCO", 0.049, 0.025, 0.476),
    ("CREDIT-CARD", 0.046, 0.041, 0.285),
    ("TIME-JOB", 0.189, 0.05, 0.128),
    ("LOW-PAY", 0.045, 0.043, 0.112),
    ("A-TEST", 0.596, 0.035, 0.052),
]
PMF_CASES = [(0.2, 0.1, 0.05), (0.5, 0.5, 0.25), (0.3, 0.25, 0.2)]
K = 100
#: A density next to none.
TINY = 1e-12


def grid(spark: SparkSession, bits=BITS, densities=DENSITIES) -> DataFrame:
    """r (resemblance) x (r1, r2) x b."""
    d = spark.createDataFrame([(float(a), float(b)) for a, b in densities], "r1 double, r2 double")
    b = spark.createDataFrame([(x,) for x in bits], "b int")
    return spark.range(1, 23).select((F.col("id") / 23.0).alias("r")).crossJoin(F.broadcast(d)).crossJoin(F.broadcast(b))


def measured(spark: SparkSession, sf: str, bits=BITS, equal: bool = False) -> DataFrame:
    """pair, r, r1, r2, f_l, f_r, a, d x b: the user sets of two event types of one day, counted in events.

    Resemblance runs over 0 < r < 1 as in the grid: pairs of sets without a common user and of equal sets have no variance.
    equal: both densities are the pair's mean."""
    e = load(spark, sf, "events").select(F.to_date("ts").cast("string").alias("day"), "event_type", "user_id").na.drop()
    users = e.select("user_id").distinct().agg(F.count("*").alias("d"))
    seen = e.groupBy("day", "user_id").agg(F.array_sort(F.collect_set("event_type")).alias("t"))  # event types of one user and day
    f = seen.select("day", F.explode("t").alias("t")).groupBy("day", "t").agg(F.count("*").alias("f"))
    both = seen.select("day", F.explode("t").alias("l"), "t").select("day", "l", F.explode("t").alias("r")).where("l < r")
    p = both.groupBy("day", "l", "r").agg(F.count("*").alias("a"))
    side = lambda s: f.select("day", F.col("t").alias(s), F.col("f").alias(f"f_{s}"))
    p = p.join(side("l"), ["day", "l"]).join(side("r"), ["day", "r"]).crossJoin(users)
    share = (lambda c: (F.col("f_l") + F.col("f_r")) / (2 * F.col("d"))) if equal else (lambda c: F.col(c) / F.col("d"))
    p = p.select(F.concat_ws(":", "day", "l", "r").alias("pair"), (F.col("a") / (F.col("f_l") + F.col("f_r") - F.col("a"))).alias("r"), share("f_l").alias("r1"), share("f_r").alias("r2"), "f_l", "f_r", "a", "d")
    b = spark.createDataFrame([(x,) for x in bits], "b int")
    return p.where("r < 1").crossJoin(F.broadcast(b))


def measured_sql(bits=BITS, equal: bool = False) -> str:
    r1, r2 = ("cast(x.f+y.f as double)/(2*d)",) * 2 if equal else ("cast(x.f as double)/d", "cast(y.f as double)/d")
    return f"""(with u as (select distinct cast(cast(ts as date) as varchar) as day, event_type as t, user_id from events where ts is not null and event_type is not null and user_id is not null),
    f as (select day, t, count(*) as f from u group by 1, 2), n as (select count(distinct user_id) as d from u),
    p as (select l.day, l.t as l, r.t as r, count(*) as a from u l join u r on l.day = r.day and l.user_id = r.user_id and l.t < r.t group by 1, 2, 3)
    select p.day || ':' || p.l || ':' || p.r as pair, cast(a as double)/(x.f+y.f-a) as r, {r1} as r1, {r2} as r2, b from p join f x on x.day = p.day and x.t = p.l join f y on y.day = p.day and y.t = p.r, n, (values {_values([(x,) for x in bits])}) v(b)
    where cast(a as double)/(x.f+y.f-a) < 1) g"""


def _values(rows) -> str:
    return ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else f"cast({x!r} as {'integer' if isinstance(x, int) else 'double'})" for x in r) + ")" for r in rows)


def grid_sql(bits=BITS, densities=DENSITIES) -> str:
    return f"(select i/cast(23 as double) as r, r1, r2, b from range(1,23) t(i), (values {_values(densities)}) d(r1,r2), (values {_values([(x,) for x in bits])}) v(b)) g"


def q(r: str, b: str) -> str:
    return f"(case when {r} < 1e-6 then power(cast(2 as double), -({b})) else {r}*power(1-{r}, power(cast(2 as double),{b})-1)/(1-power(1-{r}, power(cast(2 as double),{b}))) end)"


def floor_(b: str = "b", r1: str = "r1", r2: str = "r2") -> str:
    return f"(({q(r1, b)}*{r2}+{q(r2, b)}*{r1})/({r1}+{r2}))"


def slope_(b: str = "b", r1: str = "r1", r2: str = "r2") -> str:
    return f"(1-({q(r1, b)}*{r1}+{q(r2, b)}*{r2})/({r1}+{r2}))"


def e_(b: str = "b", r: str = "r") -> str:
    return f"({floor_(b)}+{slope_(b)}*{r})"


def var_low_(b: str = "b", k: str = "1", r: str = "r") -> str:
    return f"({e_(b, r)}*(1-{e_(b, r)})/({k}*power({slope_(b)},2)))"


def bfac_(b: str) -> str:
    return f"({b}*{var_low_(b)})"


T1 = f"(power({e_('1')},2)+power(1-{e_('1')},2))"
VAR_FOLD = f"(case when 2*{T1}-1 > 0 then {T1}*(1-{T1})/(4*KK*power({slope_('1')},2)*(2*{T1}-1)) end)"

def _cols():
    return (F.col(x) for x in ("r", "r1", "r2", "b"))


def _out(df: DataFrame, **values) -> DataFrame:
    keys = [c for c in ("pair", "b", "r1", "r2", "r") if c in df.columns]
    return df.select(*keys, *(F.round(v, 6).alias(n) for n, v in values.items()))


#: Densities counted in a table are fractions, so their closed forms can end in an exact half of the last decimal, which powers and
#: logarithms meet from either side: halves are rounded up from a little below.
HALF_UP = 1e-10


def _counted(df: DataFrame, **values) -> DataFrame:
    return _out(df, **{n: v + HALF_UP for n, v in values.items()})


def _counted_sql(source: str, **values) -> str:
    return _sql(source, _KEYS, **{n: f"{v} + {HALF_UP!r}" for n, v in values.items()})


_KEYS = "pair, b, r1, r2, r"


def _sql(source: str, keys: str = "b, r1, r2, r", where: str = "", **values) -> str:
    return f"select {keys}, {', '.join(f'round({v}, 6) as {n}' for n, v in values.items())} from {source} {where}"


def residue(spark, sf):
    r, r1, r2, b = _cols()
    return _out(grid(spark), value=theory.residue(r1, b)).drop("r").distinct()


def floor_slope(spark, sf):
    r, r1, r2, b = _cols()
    fl, sl = theory.floor_slope(r1, r2, b)
    return _counted(measured(spark, sf), floor=fl, slope=sl).drop("r")


def match_prob(spark, sf):
    r, r1, r2, b = _cols()
    return _counted(measured(spark, sf), value=theory.match_prob(r, r1, r2, b))


def chance_mass(spark, sf):
    r, r1, r2, b = _cols()
    s = r / (1 + r) * (r1 + r2)
    return _counted(measured(spark, sf), value=theory.chance_mass(r1, r2, s, b), counted=theory.match_prob_from_counts(*(F.col(c) for c in ("f_l", "f_r", "a", "d")), b))


def var_full(spark, sf):
    r, r1, r2, b = _cols()
    return _out(grid(spark), value=theory.var_full(r, K)).distinct()


def var_low(spark, sf):
    r, r1, r2, b = _cols()
    return _out(grid(spark), value=theory.var_low(r, r1, r2, b, K))


def var_fold(spark, sf):
    r, r1, r2, b = _cols()
    return _out(grid(spark, [1]), value=theory.var_fold(r, r1, r2, F.lit(K)), ratio=theory.fold_ratio(r, r1, r2))


def pmf_sum(spark, sf):
    """The joint law sums to one, and its equal-parity mass is the one-bit match probability."""
    r, r1, r2, b = _cols()
    cases = spark.createDataFrame(PMF_CASES, "r1 double, r2 double, s double")
    n = spark.range(200)
    g = n.select(F.col("id").alias("i")).crossJoin(F.broadcast(n.select(F.col("id").alias("j")))).crossJoin(F.broadcast(cases))
    p = theory.minima_pmf(F.col("i"), F.col("j"), r1, r2, F.col("s"))
    agg = g.groupBy("r1", "r2", "s").agg(F.sum(p).alias("t"), F.sum(F.when(F.col("i") % 2 == F.col("j") % 2, p)).alias("m"))
    return agg.select("r1", "r2", "s", F.round("t", 6).alias("total"), F.round("m", 6).alias("same_parity"), F.round(theory.match_prob(F.col("s") / (r1 + r2 - F.col("s")), r1, r2, F.lit(1)), 6).alias("law"))


_S = "s"
_PMF = """case when i = j then s*power(1-r1-r2+s,i) when i < j then r2*(r1-s)*power(1-r2,j-i-1)*power(1-r1-r2+s,i) else r1*(r2-s)*power(1-r1,i-j-1)*power(1-r1-r2+s,j) end"""


def storage_factor(spark, sf):
    r, r1, r2, b = _cols()
    return _out(grid(spark, densities=[(x, x) for x in EQUAL]), value=theory.storage_factor(r, r1, r2, b))


def storage_gain(spark, sf):
    r, r1, r2, b = _cols()
    return _out(grid(spark, BITS[:4], [(x, x) for x in EQUAL]), value=theory.storage_gain(r, r1, r2, F.lit(32), b))


def gain_equal(spark, sf):
    r, r1, r2, b = _cols()
    return _counted(measured(spark, sf, BITS[:4], True), value=theory.storage_gain_equal(r, r1, F.lit(32), b))


def gain_limit(spark, sf):
    r, r1, r2, b = _cols()
    return _counted(measured(spark, sf, BITS[:4], True).drop("r"), value=theory.storage_gain_limit(r1, F.lit(32), b))


def gain_onebit(spark, sf):
    r, r1, r2, b = _cols()
    return _counted(measured(spark, sf, [1], True), value=theory.storage_gain_onebit(r, r1, 32), value64=theory.storage_gain_onebit(r, r1, 64))


def inflation(spark, sf):
    r, r1, r2, b = _cols()
    return _counted(measured(spark, sf, BITS[:4]), value=theory.inflation(r, r1, r2, b))


def fold_storage(spark, sf):
    """Storage factor of one bit, how many times less the folded bit needs (0: its variance is infinite), and the permutations of both for k samples.

    A ratio, as the folded bit's own factor has a pole where one bit agrees by half."""
    r, r1, r2, b = _cols()
    return _counted(measured(spark, sf, [1]), one=theory.storage_factor(r, r1, r2, b), gain_folded=F.coalesce(theory.fold_ratio(r, r1, r2), F.lit(0.0))).withColumns({"cost_one": F.lit(theory.hash_cost(K)).cast("long"), "cost_folded": F.lit(theory.hash_cost(K, True)).cast("long")})


def words_compared(spark, sf):
    """64-bit words that comparing one pair costs, by bits and samples."""
    return spark.createDataFrame([(b, k, theory.words_compared(b, k)) for b in (1, 2, 3, 4, 32, 64) for k in (64, 100, 500)], "b long, k long, words long")


def table1_printed(spark, sf):
    r, r1, r2, b = _cols()
    df = spark.createDataFrame(PRINTED, "pair string, r1 double, r2 double, r double")
    return _out(df, gain32=theory.storage_gain(r, r1, r2, F.lit(32), F.lit(1)), gain64=theory.storage_gain(r, r1, r2, F.lit(64), F.lit(1)))


def headlines(spark, sf):
    """The headline numbers, each from its closed form: in their limits of density, and at every density measured (r1 = r2)."""
    d = measured(spark, sf, [1], True).select("pair", F.col("r1").alias("x")).unionByName(spark.createDataFrame([("limit", TINY)], "pair string, x double"))
    x = F.col("x")
    rows = {
        "gain of one bit over 64, R = 0.5": theory.storage_gain_onebit(0.5, x, 64),
        "gain of one bit over 32, R = 0.5": theory.storage_gain_onebit(0.5, x, 32),
        "gain of one bit over 32, R near 1": theory.storage_gain_onebit(1.0, x, 32),
        "gain of one bit over 64, R near 1": theory.storage_gain_onebit(1.0, x, 64),
        "greatest gain of one bit over 64": F.lit(theory.storage_gain_onebit(1.0, 1.0, 64)),
        "variance inflation of one bit, R = 0.5": theory.inflation(F.lit(0.5), x, x, F.lit(1)),
        "folded bit breaks even with one bit": planner.fold_breakeven_closed(x, x),
        "limit of one bit over folded variance": F.lit(2.0),
    }
    each = F.explode(F.array(*(F.struct(F.lit(n).alias("name"), F.round(v + HALF_UP, 5).alias("value")) for n, v in rows.items()))).alias("v")
    return d.select("pair", each).select("pair", "v.name", "v.value")


_HALF = f"({floor_('1', 'x', 'x')}+{slope_('1', 'x', 'x')}*0.5)"
HEADLINES_SQL = f"""with d as (select pair, r1 as x from {measured_sql([1], True)} union all select 'limit', cast({TINY!r} as double))
 select pair, name, round(value + {HALF_UP!r}, 5) as value from d, lateral (values
 ('gain of one bit over 64, R = 0.5', 32/(1.5-x)),
 ('gain of one bit over 32, R = 0.5', 16/(1.5-x)),
 ('gain of one bit over 32, R near 1', 32/(2-x)),
 ('gain of one bit over 64, R near 1', 64/(2-x)),
 ('greatest gain of one bit over 64', cast(64 as double)),
 ('variance inflation of one bit, R = 0.5', {_HALF}*(1-{_HALF})/(power({slope_('1', 'x', 'x')},2)*0.25)),
 ('folded bit breaks even with one bit', ((1+1/sqrt(cast(3 as double)))/2-{floor_('1', 'x', 'x')})/{slope_('1', 'x', 'x')}),
 ('limit of one bit over folded variance', cast(2 as double))) t(name, value)"""


def best_b(spark, sf):
    """The number of bits with the least storage factor, by pair."""
    r, r1, r2, b = _cols()
    g = measured(spark, sf, planner.CANDIDATES).withColumn("v", F.round(theory.storage_factor(r, r1, r2, b), 9))
    return g.groupBy("pair", "r1", "r2", "r").agg(F.min_by("b", F.struct("v", "b")).cast("int").alias("best"))


def sample_size(spark, sf):
    """Samples for a standard deviation of 0.05."""
    r, r1, r2, b = _cols()
    return measured(spark, sf, BITS[:4]).select("pair", "b", "r1", "r2", "r", F.ceil(F.round(theory.var_low(r, r1, r2, b, 1) / 0.0025, 6)).cast("long").alias("k"))


QUERIES = {
    f"theory_{f.__name__}": f
    for f in (residue, floor_slope, match_prob, chance_mass, var_full, var_low, var_fold, pmf_sum, storage_factor, storage_gain, gain_equal, gain_limit, gain_onebit, inflation, fold_storage, words_compared, table1_printed, headlines)
} | {"planner_best_b": best_b, "planner_sample_size": sample_size}

_EQ = [(x, x) for x in EQUAL]
_Q1, _Q32 = q("r1", "b"), q("r1", "32")
_SS = "(r/(1+r)*(r1+r2))"
ORACLES = {
    "theory_residue": f"select distinct b, r1, r2, round({q('r1', 'b')}, 6) as value from {grid_sql()}",
    "theory_floor_slope": f"select pair, b, r1, r2, round({floor_()} + {HALF_UP!r}, 6) as floor, round({slope_()} + {HALF_UP!r}, 6) as slope from {measured_sql()}",
    "theory_match_prob": _counted_sql(measured_sql(), value=e_()),
    "theory_chance_mass": _counted_sql(measured_sql(), value=f"({q('r1', 'b')}*(r2-{_SS})+{q('r2', 'b')}*(r1-{_SS}))/(r1+r2-{_SS})", counted=e_()),
    "theory_var_full": f"select distinct b, r1, r2, r, round(r*(1-r)/{K}, 6) as value from {grid_sql()}",
    "theory_var_low": _sql(grid_sql(), value=var_low_(k=str(K))),
    "theory_var_fold": _sql(grid_sql([1]), value=VAR_FOLD.replace("KK", str(K)), ratio=f"{var_low_('1')}/{VAR_FOLD.replace('KK', '1')}"),
    "theory_pmf_sum": f"select r1, r2, s, round(sum({_PMF}),6) as total, round(sum(case when i%2=j%2 then {_PMF} end),6) as same_parity, round(any_value({e_('1', '(s/(r1+r2-s))')}),6) as law from range(200) x(i), range(200) y(j), (values {_values(PMF_CASES)}) c(r1,r2,s) group by r1, r2, s",
    "theory_storage_factor": _sql(grid_sql(densities=_EQ), value=bfac_("b")),
    "theory_storage_gain": _sql(grid_sql(BITS[:4], _EQ), value=f"{bfac_('32')}/{bfac_('b')}"),
    "theory_gain_equal": _counted_sql(measured_sql(BITS[:4], True), value=f"(32*({_Q32}+(1-{_Q32})*r)*(1-{_Q1}))/(b*({_Q1}+(1-{_Q1})*r)*(1-{_Q32}))"),
    "theory_gain_limit": f"select pair, b, r1, r2, round(cast(32 as double)/b*(1-{_Q1})/(1-{_Q32}) + {HALF_UP!r}, 6) as value from {measured_sql(BITS[:4], True)}",
    "theory_gain_onebit": _counted_sql(measured_sql([1], True), value="32*r/(r+1-r1)", value64="64*r/(r+1-r1)"),
    "theory_inflation": _counted_sql(measured_sql(BITS[:4]), value=f"{var_low_()}/(r*(1-r))"),
    "theory_words_compared": "select cast(b as bigint) as b, cast(k as bigint) as k, cast(b * ceil(k / cast(64 as double)) as bigint) as words from (values (1), (2), (3), (4), (32), (64)) x(b), (values (64), (100), (500)) y(k)",
    "theory_fold_storage": f"select pair, b, r1, r2, r, round({bfac_('1')} + {HALF_UP!r}, 6) as one, round(coalesce({var_low_('1')}/{VAR_FOLD.replace('KK', '1')}, 0) + {HALF_UP!r}, 6) as gain_folded, cast({K} as bigint) as cost_one, cast({2 * K} as bigint) as cost_folded from {measured_sql([1])}",
    "theory_table1_printed": f"select pair, r1, r2, r, round({bfac_('32')}/{bfac_('1')}, 6) as gain32, round({bfac_('64')}/{bfac_('1')}, 6) as gain64 from (values {_values(PRINTED)}) t(pair, r1, r2, r)",
    "theory_headlines": HEADLINES_SQL,
    "planner_best_b": f"select pair, r1, r2, r, b as best from (select *, row_number() over (partition by pair order by round({bfac_('b')}, 9), b) as n from {measured_sql(planner.CANDIDATES)}) where n = 1",
    "planner_sample_size": f"select pair, b, r1, r2, r, cast(ceil(round({var_low_()}/0.0025, 6)) as bigint) as k from {measured_sql(BITS[:4])}",
}
assert math.isclose(theory.residue(1e-10, 3), 0.125, abs_tol=1e-9)
