"""The experiments, on the given tables: bias and error of the estimators, retrieval by threshold, space gains."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import theory
from ..functions.hashing import PRIME
from ..operators import blocks, estimators, exact, metrics, pairs, planes, ranks, sets, signature, simulate
from ..sources.io import load, stored

#: Word pairs of documents that stand in for the ten pairs of the experiment, in its order.
PAIRS = [("eaedin", "thingstsh"), ("thanea", "eriner"), ("the", "that"), ("achkeitein", "enieau"), ("por", "ñ"), ("erreth", "edouhe"), ("enver", "chver"), ("erth", "esnd"), ("ntin", "ntes"), ("en", "erß")]
#: f1, f2, a of these pairs among 1000 documents.
COUNTS = [(15, 14, 14), (146, 145, 134), (615, 484, 479), (4, 3, 3), (63, 55, 44), (47, 27, 24), (45, 41, 19), (189, 50, 27), (45, 43, 9), (582, 35, 30)]
UNIVERSE = 1000
FOLD_PAIRS = (0, 2, 4, 8)
KS, REPS = [10, 20, 50, 100, 200], 25000
CURVE_KS, CURVE_REPS = [64, 128, 256], 2
OWN_K, OWN_REPS = 50, 100
GAIN_KS = [*range(16, 257, 16), 320, 384, 448, 512]
WORD_THRESHOLDS, DOC_THRESHOLDS = [0.3, 0.4, 0.5, 0.6, 0.7, 0.8], [0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9]


def stand_ins() -> list[dict]:
    return [{"pair": f"{x}-{y}", "f1": f1, "f2": f2, "a": a, "D": UNIVERSE} for (x, y), (f1, f2, a) in zip(PAIRS, COUNTS)]


def table1_data(spark: SparkSession, sf: str) -> DataFrame:
    """f1, f2, a, resemblance, floor, slope and storage gains of the word pairs, counted in documents."""
    docs = load(spark, sf, "documents")
    wanted = F.broadcast(spark.createDataFrame([(x, y) for x, y in PAIRS], "w1 string, w2 string"))
    words = sorted({w for p in PAIRS for w in p})
    p = sets.postings(docs).where(F.col("set_id").isin(words))
    f = sets.sizes(p)
    both = p.alias("x").join(wanted, F.col("x.set_id") == F.col("w1")).join(p.alias("y"), (F.col("y.set_id") == F.col("w2")) & (F.col("x.elem") == F.col("y.elem")))
    a = both.groupBy("w1", "w2").agg(F.count("*").alias("a"))
    t = a.join(f.select(F.col("set_id").alias("w1"), F.col("f").alias("f1")), "w1").join(f.select(F.col("set_id").alias("w2"), F.col("f").alias("f2")), "w2")
    t = t.crossJoin(docs.agg(F.count("*").alias("d"))).withColumns({"r1": F.col("f1") / F.col("d"), "r2": F.col("f2") / F.col("d"), "r": F.col("a") / (F.col("f1") + F.col("f2") - F.col("a"))})
    r, r1, r2 = F.col("r"), F.col("r1"), F.col("r2")
    fl, sl = theory.floor_slope(r1, r2, F.lit(1))
    gain = lambda b: F.round(theory.storage_gain(r, r1, r2, F.lit(b), F.lit(1)), 4)
    return t.select("w1", "w2", "f1", "f2", "a", F.round(r, 6).alias("r"), F.round(fl, 6).alias("floor"), F.round(sl, 6).alias("slope"), gain(32).alias("gain32"), gain(64).alias("gain64"))


def counted(spark: SparkSession, sf: str, which=range(len(PAIRS))) -> list[dict]:
    """f1, f2, a and D of the word pairs as counted in the given documents; pairs that never meet there have no row."""
    size = load(spark, sf, "documents").count()
    found = {(r.w1, r.w2): r for r in table1_data(spark, sf).collect()}
    return [{"pair": "-".join(p), "f1": found[p].f1, "f2": found[p].f2, "a": found[p].a, "D": size} for p in (PAIRS[i] for i in which) if p in found]


def bias_mse(spark: SparkSession, sf: str, reps: int = REPS, ks=KS) -> DataFrame:
    return simulate.bias_mse(spark, counted(spark, sf), ks, reps)


def fold_mse(spark: SparkSession, sf: str, reps: int = REPS, ks=KS) -> DataFrame:
    return simulate.bias_mse(spark, counted(spark, sf, FOLD_PAIRS), ks, reps, (1,), True)


def signature_bias(spark: SparkSession, sf: str, k: int = OWN_K, reps: int = OWN_REPS, bs=(1, 2, 3)) -> DataFrame:
    """As bias_mse, but every repetition takes k true permutations of the given documents through the word sets' own minima."""
    docs = load(spark, sf, "documents").select("doc_id", "text")
    words = sorted({x for p in PAIRS for x in p})
    s = stored(sets.postings(docs).where(F.col("set_id").isin(words)), "words")
    universe = stored(docs.where(F.lower("text").rlike(r"[\p{L}\p{N}]")).select(F.col("doc_id").alias("elem")).distinct(), "universe")  # documents with a word
    size = universe.count()
    z = stored(ranks.minima(s, k * reps, 0, universe).select("set_id", "f", F.posexplode("z").alias("j", "z")), "ranks")
    wanted = F.broadcast(spark.createDataFrame([(*p, "-".join(p)) for p in PAIRS], "w1 string, w2 string, pair string"))
    x, y = z.alias("x"), z.alias("y")
    met = x.join(wanted, F.col("x.set_id") == F.col("w1")).join(y, (F.col("y.set_id") == F.col("w2")) & (F.col("x.j") == F.col("y.j")))
    apart = F.col("x.z").bitwiseXOR(F.col("y.z"))
    shares = [F.avg((apart == 0).cast("int")).alias("e32"), *(F.avg((apart.bitwiseAND(F.lit((1 << b) - 1)) == 0).cast("int")).alias(f"e{b}") for b in bs)]
    drawn = met.groupBy("pair", "w1", "w2", F.floor(F.col("x.j") / k).alias("rep"), F.col("x.f").alias("f1"), F.col("y.f").alias("f2")).agg(*shares)
    truth = exact.of_pairs(s, spark.createDataFrame(PAIRS, "id_l string, id_r string")).select(F.col("id_l").alias("w1"), F.col("id_r").alias("w2"), "r")
    each = F.explode(F.array(F.struct(F.lit("full").alias("estimator"), F.lit(32).alias("b"), F.col("e32").alias("e_hat")), *(F.struct(F.lit("low").alias("estimator"), F.lit(b).alias("b"), F.col(f"e{b}").alias("e_hat")) for b in bs))).alias("e")
    d = drawn.join(truth, ["w1", "w2"]).select("pair", "rep", "r", (F.col("f1") / F.lit(float(size))).alias("r1"), (F.col("f2") / F.lit(float(size))).alias("r2"), each).select("pair", "rep", "r", "r1", "r2", "e.*", F.lit(k).alias("k"))
    d = stored(d, "drawn")
    guess = F.when(F.col("estimator") == "full", F.col("e_hat"))
    for b in bs:
        floor, slope = theory.floor_slope(F.col("r1"), F.col("r2"), b)
        guess = guess.when(F.col("b") == b, (F.col("e_hat") - floor) / slope)
    points = metrics.bias_mse(stored(d.withColumn("r_hat", guess), "guesses"), ["pair", "estimator", "b", "k", "r", "r1", "r2"])
    return simulate.theory_variance(points).select("pair", "estimator", "b", "k", "reps", *(F.round(c, 6).alias(c) for c in ("bias", "variance", "mse", "theory")))


def retrieval(s: DataFrame, kind: str, domain: float, ks: list[int], bs: list[int], full_bits: int, thresholds: list[float], reps: int = 1) -> DataFrame:
    """Precision and recall of every estimator, k and threshold over all pairs of sets, averaged over repetitions.

    What each estimate retrieves is counted where blocks of sets meet, so only counts leave the tasks.  Relevant pairs come from an
    exact count (of few sets) or prefix join; their estimates say how many of them are hit.  Each repetition has permutations of its own."""
    s = stored(s, "sets")
    few = kind == "perm"  # sets of a bounded vocabulary, which may hold most elements each
    truth = exact.of_few(s).where(F.col("r") >= min(thresholds)) if few else pairs.prefix_join(s, min(thresholds))
    truth = stored(truth.select("id_l", "id_r", "r"), "truth")
    curves = None
    for rep in range(reps):
        full = ranks.minima(s, max(ks), rep, together=True) if few else signature.build_full(s, kind, max(ks), rep)
        sig = stored(planes.from_full(full, max(ks), full_bits), "planes")
        side = lambda x: sig.select(F.col("set_id").alias(f"id_{x}"), F.col("f").alias(f"f_{x}"), *(F.col(f"plane_{i}").alias(f"{x}_{i}") for i in range(full_bits)))  # noqa: E731, B023
        hits = blocks.hits(truth.join(side("l"), "id_l").join(side("r"), "id_r").drop("id_l", "id_r"), ks, bs, full_bits, domain, thresholds)
        found = blocks.retrieved(sig, ks, bs, full_bits, domain, thresholds)
        c = metrics.with_ratios(found.join(hits, ["estimator", "b", "k", "r0"], "left").na.fill(0, ["n_rel", "n_hit"])).withColumn("rep", F.lit(rep))
        curves = c if curves is None else curves.unionByName(c)
    total = [F.sum(n).alias(n) for n in ("n_rel", "n_ret", "n_hit")]
    return curves.groupBy("estimator", "b", "k", "r0").agg(*total, F.avg("precision").alias("precision"), F.avg("recall").alias("recall"), F.stddev_pop("precision").alias("precision_sd"), F.stddev_pop("recall").alias("recall_sd"))


def _rounded(c: DataFrame) -> DataFrame:
    return c.select("estimator", "b", "k", "r0", "n_rel", "n_ret", "n_hit", *(F.round(x, 6).alias(x) for x in ("precision", "recall", "precision_sd", "recall_sd")))


def word_sets(spark: SparkSession, sf: str) -> DataFrame:
    return sets.postings(load(spark, sf, "documents").select("doc_id", "text"), top_n=2633)


def word_curve(spark, sf, ks, reps: int = CURVE_REPS) -> DataFrame:
    s = word_sets(spark, sf)
    d = s.select("elem").distinct().count()
    return retrieval(s, "perm", d, list(ks), [1, 2, 3, 4], max(5, (d - 1).bit_length()), WORD_THRESHOLDS, reps)


def pr_words(spark: SparkSession, sf: str) -> DataFrame:
    """All pairs of the 2633 commonest words, by documents they occur in: counts summed and ratios averaged over repetitions."""
    return _rounded(word_curve(spark, sf, CURVE_KS))


def space_gain(spark: SparkSession, sf: str, ks=GAIN_KS, reps: int = CURVE_REPS) -> DataFrame:
    """Space of 32-bit samples over space of b-bit samples at equal precision, by threshold."""
    g = metrics.space_gain(word_curve(spark, sf, ks, reps), [0.7, 0.8])
    return g.select("r0", "target", "b", "k_low", "k_full", F.round("gain", 4).alias("gain"))


def pr_docs(spark: SparkSession, sf: str) -> DataFrame:
    """All pairs of documents, by 5-word shingles."""
    s = sets.shingles(load(spark, sf, "documents").select("doc_id", "text"))
    return _rounded(retrieval(s, "affine31", float(PRIME), CURVE_KS, [1, 2, 4], 31, DOC_THRESHOLDS, CURVE_REPS))
