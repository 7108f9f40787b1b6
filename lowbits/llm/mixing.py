"""Mixing sources to target weights: temperature mixing (operator 2).

Each source's share of all tokens is raised to an exponent and normalised.  The exponent is the largest in
[0, 1] (the one nearest to natural proportions) for which the weights reach the target entropy, as a share of
log(number of sources), and, where a budget and a repetition limit are given, for as long as no source
is repeated more often than the limit allows; found by bisection.  Every source's token budget is realised as
passes over its blocks: documents are dealt to blocks by a hash of their id, each pass orders the
blocks by a hash of its own, and the last pass stops at the block that meets the budget best.

Edge cases: a null source is a source of its own; null or empty texts have no tokens and are never drawn;
sources without tokens get weight 0; one source gets weight 1; an empty table gives an empty
table.  Equal hashes are ordered by block number.  Rows with equal or null ids share a block.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .engine import stored

BLOCKS, STEPS, BROADCAST_ROWS = 256, 50, 100_000
TARGET_ENTROPY, REPETITIONS = 0.95, 4.0


def _digest(*parts) -> F.Column:
    """A 60-bit number from md5 of the parts, portable to other engines."""
    text = F.concat_ws(":", *(F.coalesce(p.cast("string"), F.lit("")) for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def token_count(text) -> F.Column:
    """Runs of other characters than space and controls 9 to 13; null: 0."""
    trimmed = F.regexp_replace(text, r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "")
    return F.when(F.coalesce(F.length(trimmed), F.lit(0)) == 0, F.lit(0)).otherwise(F.size(F.split(trimmed, r"[\x20\x09-\x0D]+"))).cast("long")


def weights_at(shares: list[float], exponent: float) -> list[float]:
    raised = [s**exponent if s > 0 else 0.0 for s in shares]
    total = sum(raised)
    return [r / total for r in raised] if total else raised


def entropy(weights: list[float], copies: list[int] | None = None) -> float:
    """Entropy of weights, each held by as many sources as copies says (one)."""
    return -sum(n * w * math.log(w) for w, n in zip(weights, copies or [1] * len(weights)) if w > 0)


def solve_exponent(tokens: list[int], target_entropy: float | None, repetitions: float | None, budget: float, copies: list[int] | None = None) -> float:
    """Bisected exponent in [0, 1].  Entropy falls as it grows; repetitions of small sources fall too.

    copies: how many sources have so many tokens (one).  The repetition limit, if it binds, gives the least exponent; the
    entropy target the greatest.  Where both can't be met the repetition limit wins, as it protects from overfitting."""
    copies = copies or [1] * len(tokens)
    live = [(t, n) for t, n in zip(tokens, copies) if t > 0]
    tokens, copies, sources = [t for t, _ in live], [n for _, n in live], sum(n for _, n in live)
    if sources < 2:
        return 1.0
    total = sum(t * n for t, n in live)

    def weights(x: float) -> list[float]:
        raised = [(t / total) ** x for t in tokens]
        whole = sum(r * n for r, n in zip(raised, copies))
        return [r / whole for r in raised]

    def bisect(ok_low) -> tuple[float, float]:
        lo, hi = 0.0, 1.0
        for _ in range(STEPS):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if ok_low(mid) else (lo, mid)
        return lo, hi

    best = 1.0
    if target_entropy is not None:
        reached = lambda x: entropy(weights(x), copies) >= target_entropy * math.log(sources)
        best = 1.0 if reached(1.0) else bisect(reached)[0]
    if repetitions is not None:
        over = lambda x: max(budget * w / t for w, t in zip(weights(x), tokens)) > repetitions
        if over(best):
            least = bisect(over)[1] if not over(1.0) else 1.0
            best = max(best, least)
    return best


def source_weights(tokens: DataFrame, target_entropy: float | None = TARGET_ENTROPY, repetitions: float | None = REPETITIONS, budget_share: float = 1.0) -> DataFrame:
    """source, tokens, share, weight, exponent, budget (tokens to draw).  tokens has source and n_tokens.

    The driver sees how many sources have which number of tokens: with T tokens in all at most sqrt(2 T) rows, however many sources."""
    each = stored(tokens.groupBy("source").agg(F.coalesce(F.sum("n_tokens"), F.lit(0)).cast("long").alias("tokens")), "sources")
    sizes = each.groupBy("tokens").agg(F.count("*").alias("n")).orderBy("tokens").collect()
    counts, copies = [int(r.tokens) for r in sizes], [int(r.n) for r in sizes]
    total = sum(t * n for t, n in zip(counts, copies))
    x = solve_exponent(counts, target_entropy, repetitions, budget_share * total, copies)
    whole = sum(n * (t / total) ** x for t, n in zip(counts, copies) if t > 0)
    share = F.col("tokens") / F.lit(float(total or 1))
    weight = F.when(F.col("tokens") > 0, F.pow(share, F.lit(x)) / F.lit(whole or 1.0)).otherwise(F.lit(0.0))
    return each.select("source", "tokens", share.alias("share"), weight.alias("weight"), F.lit(x).alias("exponent"), (F.lit(budget_share * total) * weight).alias("budget"))


def mix(docs: DataFrame, target_entropy: float | None = TARGET_ENTROPY, repetitions: float | None = REPETITIONS, budget_share: float = 1.0, seed: int = 7, blocks: int = BLOCKS, keep: tuple[str, ...] = (), broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """doc_id, source, n_tokens, block, pass, position, weight, exponent and the columns of docs named in keep: one row per
    document and pass it is drawn in.

    position orders the draws of a source's blocks over all passes; it is the running token count of
    the source before the block, so merging sources by position / budget interleaves them."""
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["source"].cast("string").alias("source"), token_count(docs["text"]).alias("n_tokens"), *(docs[c] for c in keep))
    rows = stored(rows.withColumn("block", (_digest(F.lit(seed), F.col("doc_id")) % blocks).cast("int")), "tokens")  # texts are tokenised once
    sums = stored(rows.groupBy("source", "block").agg(F.sum("n_tokens").alias("block_tokens")), "blocks")
    weights = source_weights(sums.withColumnRenamed("block_tokens", "n_tokens"), target_entropy, repetitions, budget_share)
    plan = sums.join(weights, sums["source"].eqNullSafe(weights["source"])).select(sums["source"], "block", "block_tokens", "tokens", "weight", "exponent", "budget")
    plan = plan.withColumn("pass", F.explode(F.sequence(F.lit(0), F.ceil(F.col("budget") / F.greatest(F.col("tokens"), F.lit(1))).cast("int"))))
    order = Window.partitionBy("source").orderBy("pass", _digest(F.lit(seed), F.col("source"), F.col("pass"), F.col("block")), "block").rowsBetween(Window.unboundedPreceding, -1)  # blocks x passes of one source
    plan = plan.withColumn("position", F.coalesce(F.sum("block_tokens").over(order), F.lit(0)))
    chosen = stored(plan.where("block_tokens > 0 and position + block_tokens / 2 <= budget").select(F.col("source").alias("s"), F.col("block").alias("b"), "pass", "position", "weight", "exponent"), "plan")
    if chosen.limit(broadcast_rows + 1).count() <= broadcast_rows:
        chosen = F.broadcast(chosen)
    out = rows.where("n_tokens > 0").join(chosen, rows["source"].eqNullSafe(chosen["s"]) & (rows["block"] == chosen["b"]))
    return out.select("doc_id", "source", "n_tokens", "block", "pass", "position", "weight", "exponent", *(rows[c] for c in keep))
