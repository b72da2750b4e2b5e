"""Mixing sources to target weights: tokens by source, repetition rates, whole copies and one seeded Bernoulli copy.

The size of a document is the number of its words (null: 0). Sources stand in code point order, null last, and their weights repeat the
given pattern. They share a budget of a given part of all words; no target exceeds max_rate times its source's words, and what is cut
is shared anew by weight until no target is above. The targets have a closed form, min(cap, level x weight): the sources in the order
of cap / weight fill up one by one, so one cumulative sum over the (aggregated) sources finds the level.

Each document is taken floor(rate) times, and once more when a hash of its id and the seed falls under the fraction. Reruns agree.
Equal rows make equal choices. A null id is replaced by a hash of the text, a null text has size 0. Sources of no words have target 0
and rate 0 (their documents, all empty, are not taken). Empty tables give empty results. The input may have any further columns;
the working columns start with "_mix".
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

WEIGHTS, SHARE, MAX_RATE, SEED = (5, 2, 1), 1.5, 2, 20_11
_WORD = r"[^\x20\x09-\x0D]+"
#: Up to so many sources their targets are broadcast; beyond it Spark chooses a join.
BROADCAST_SOURCES = 10_000


def word_count(text: str = "text"):
    return F.coalesce(F.regexp_count(F.col(text), F.lit(_WORD)), F.lit(0)).cast("long")


def source_targets(sized: DataFrame, weights: Sequence[float] = WEIGHTS, share: float = SHARE, max_rate: float = MAX_RATE) -> DataFrame:
    """source, source_size, target for rows (source, size). Windows here run over one row for each source."""
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    one = Window.partitionBy(F.lit(0))
    ranked = totals.withColumn("_rank", F.row_number().over(one.orderBy(F.col("source").asc_nulls_last())))
    weighed = ranked.withColumn("_w", F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (F.pmod(F.col("_rank") - 1, F.lit(len(weights))) + 1).cast("int")))
    budget = weighed.withColumn("_budget", F.sum("source_size").over(one) * F.lit(float(share))).withColumn("_cap", F.col("source_size") * F.lit(float(max_rate)))
    order = one.orderBy(F.col("_cap") / F.col("_w"), "_rank").rowsBetween(Window.unboundedPreceding, -1)
    filled = budget.withColumn("_below", F.coalesce(F.sum("_cap").over(order), F.lit(0.0))).withColumn("_left", F.sum("_w").over(one) - F.coalesce(F.sum("_w").over(order), F.lit(0.0)))
    # The level is set by the first source that the rest of the budget does not fill to its cap.
    level = F.when((F.col("_budget") - F.col("_below")) / F.col("_left") < F.col("_cap") / F.col("_w"), (F.col("_budget") - F.col("_below")) / F.col("_left"))
    targets = filled.withColumn("_level", F.max(level).over(one))
    return targets.select("source", "source_size", F.least(F.col("_cap"), F.coalesce(F.col("_level") * F.col("_w"), F.col("_cap"))).alias("target"))


def with_copies(docs: DataFrame, weights: Sequence[float] = WEIGHTS, share: float = SHARE, max_rate: float = MAX_RATE, seed: int = SEED, keep: Sequence[str] | None = None) -> DataFrame:
    """keep columns of docs (default: all) with _mix_size, _mix_source_size, _mix_target and _mix_copies, the number of times the mix takes the row."""
    kept = list(docs.columns if keep is None else keep)
    ident = F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("text "), F.md5(F.coalesce("text", F.lit(""))))))
    toss = F.conv(F.substring(F.md5(ident), 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))
    sized = docs.select(*kept, *([] if "source" in kept else ["source"]), word_count().alias("_mix_size"), toss.alias("_mix_toss"))
    targets = source_targets(sized.select("source", F.col("_mix_size").alias("size")), weights, share, max_rate).select(F.col("source").alias("_mix_key"), F.col("source_size").alias("_mix_source_size"), F.col("target").alias("_mix_target"))
    targets = F.broadcast(targets) if targets.count() <= BROADCAST_SOURCES else targets
    rate = F.when(F.col("_mix_source_size") > 0, F.col("_mix_target") / F.col("_mix_source_size")).otherwise(0.0)
    copies = F.floor(rate) + (F.col("_mix_toss") < rate - F.floor(rate)).cast("long")
    mixed = sized.join(targets, F.col("source").eqNullSafe(F.col("_mix_key"))).withColumn("_mix_copies", copies)
    return mixed.select(*kept, "_mix_size", "_mix_source_size", "_mix_target", "_mix_copies")


def mix(docs: DataFrame, **how) -> DataFrame:
    """The mix itself: each row of docs as many times as it is taken."""
    taken = with_copies(docs, **how)
    return taken.withColumn("_mix_copy", F.explode(F.when(F.col("_mix_copies") > 0, F.sequence(F.lit(1), F.col("_mix_copies").cast("int"))))).select(*docs.columns)


def mix_report(docs: DataFrame, **how) -> DataFrame:
    """doc_id, size, source_size, target, taken for each row of docs."""
    rows = with_copies(docs, keep=["doc_id"], **how)
    return rows.select("doc_id", F.col("_mix_size").alias("size"), F.col("_mix_source_size").alias("source_size"), F.col("_mix_target").alias("target"), (F.col("_mix_size") * F.col("_mix_copies")).alias("taken"))
