"""Scores and measures over long-form gold and predictions.

Every score returns one row per key with a value in [0, 1].  Totals of gold are aggregated once
and joined to hits; gold is never repeated for each system.  Formulas that the text leaves open
are design decisions, marked [D].
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def f1(hit: Column, predicted: Column, gold: Column) -> Column:
    """Harmonic mean from weights; 1 if both sides are empty, 0 if one is. [D]"""
    return F.when((predicted == 0) & (gold == 0), F.lit(1.0)).otherwise(2.0 * hit / (predicted + gold))


def _systems(pred: DataFrame, systems: DataFrame | None, by: str) -> DataFrame:
    """The systems to score; without a list, those that answered anything."""
    return F.broadcast((pred if systems is None else systems).select(by).distinct())


def severity_f1(pred: DataFrame, gold: DataFrame, *, key: str = "patient_id", item: str = "dx_id", by: str = "m", neutral: DataFrame | None = None, weight: str = "weight", extra: float = 1.0, systems: DataFrame | None = None) -> DataFrame:
    """(by, key, value): gold items weigh by severity, penalized extras weigh ``extra``. [D]

    With ``neutral`` (key, item: what the chart documents), documented extras are not penalized.
    Duplicate predictions count once; every one of ``systems`` scores on every gold key, 0 if silent.
    """
    gold = gold.select(key, item, F.col(weight).cast("double").alias("_w"))
    rows = pred.select(by, key, item).distinct().join(gold, [key, item], "left")
    free = F.col("_w").isNotNull()
    if neutral is not None:
        rows = rows.join(neutral.select(key, item, F.lit(True).alias("_told")).distinct(), [key, item], "left")
        free = free | F.col("_told").isNotNull()
    per = rows.groupBy(by, key).agg(F.sum(F.coalesce("_w", F.lit(0.0))).alias("_hit"), F.sum(F.when(free, F.lit(0.0)).otherwise(F.lit(extra))).alias("_extra"))
    every = gold.groupBy(key).agg(F.sum("_w").alias("_gold")).crossJoin(_systems(pred, systems, by))
    out = every.join(per, [by, key], "left").fillna(0.0, ["_hit", "_extra"])
    return out.select(by, key, F.coalesce(f1(F.col("_hit"), F.col("_hit") + F.col("_extra"), F.col("_gold")), F.lit(0.0)).alias("value"))


def set_prf(pred: DataFrame, gold: DataFrame, *, keys: list[str], item: str, by: str = "m", instances: DataFrame | None = None, systems: DataFrame | None = None) -> DataFrame:
    """(by, keys, hit, n_pred, n_gold, precision, recall, value) of distinct item sets.

    ``instances`` lists the keys to score; without it, those that have gold.  Empty gold and an
    empty prediction is a right abstention and scores 1.
    """
    gold = gold.select(*keys, item).distinct()
    rows = pred.select(by, *keys, item).distinct().join(gold.withColumn("_in", F.lit(1)), [*keys, item], "left")
    per = rows.groupBy(by, *keys).agg(F.count("_in").alias("hit"), F.count("*").alias("n_pred"))
    n_gold = gold.groupBy(*keys).agg(F.count("*").alias("n_gold"))
    every = n_gold if instances is None else instances.select(*keys).distinct().join(n_gold, keys, "left")
    out = every.crossJoin(_systems(pred, systems, by)).join(per, [by, *keys], "left").fillna(0, ["hit", "n_pred", "n_gold"])
    zero = F.lit(0.0)
    return out.withColumns({
        "precision": F.when(F.col("n_pred") > 0, F.col("hit") / F.col("n_pred")).otherwise(zero),
        "recall": F.when(F.col("n_gold") > 0, F.col("hit") / F.col("n_gold")).otherwise(zero),
        "value": f1(F.col("hit"), F.col("n_pred"), F.col("n_gold")),
    })


def macro(scores: DataFrame, by: str = "m", value: str = "value", name: str = "score") -> DataFrame:
    return scores.groupBy(by).agg(F.round(F.avg(value), 6).alias(name), F.count("*").alias("n"))


def precision_at(ranked: DataFrame, grades: DataFrame, *, key: str = "patient_id", item: str = "section_id", by: str = "m", k: int = 5, min_grade: int = 2, systems: DataFrame | None = None) -> DataFrame:
    """Share of the first k (always k, short lists are penalized) with a grade of ``min_grade`` at least; 0 where nothing is ranked."""
    top = ranked.where(F.col("rank") <= k).join(grades, [key, item], "left")
    out = top.groupBy(by, key).agg((F.sum((F.coalesce("grade", F.lit(0)) >= min_grade).cast("int")) / k).alias("value"))
    return complete(grades, _systems(ranked, systems, by), out, key=key, by=by)


def gain(kind: str) -> Column:
    return F.pow(F.lit(2.0), F.coalesce("grade", F.lit(0))) - 1 if kind == "exp" else F.coalesce("grade", F.lit(0)).cast("double")


def ndcg_at(ranked: DataFrame, grades: DataFrame, *, key: str = "patient_id", item: str = "section_id", by: str = "m", k: int = 10, kind: str = "exp", systems: DataFrame | None = None) -> DataFrame:
    """Normalized discounted gain, 0 where nothing is ranked; keys whose grades are all zero have no score."""
    discount = F.log2(F.col("rank") + 1.0)
    got = ranked.where(F.col("rank") <= k).join(grades, [key, item], "left").groupBy(by, key).agg(F.sum(gain(kind) / discount).alias("_dcg"))
    order = F.row_number().over(Window.partitionBy(key).orderBy(F.desc("grade"), item))
    best = grades.withColumn("rank", order).where(F.col("rank") <= k).groupBy(key).agg(F.sum(gain(kind) / discount).alias("_ideal"))
    best = best.where("_ideal > 0")
    out = got.join(best, key).select(by, key, (F.col("_dcg") / F.col("_ideal")).alias("value"))
    return complete(best, _systems(ranked, systems, by), out, key=key, by=by)


def rank_metrics(ranked: DataFrame, grades: DataFrame, *, key: str = "patient_id", item: str = "section_id", by: str = "m", k: int = 10, min_grade: int = 2, systems: DataFrame | None = None) -> DataFrame:
    """Reciprocal rank, average precision and recall at k of keys that have a relevant item."""
    rel = grades.where(F.col("grade") >= min_grade).select(key, item)
    total = rel.groupBy(key).agg(F.count("*").alias("_n"))
    hits = ranked.join(rel, [key, item]).withColumn("_k", F.row_number().over(Window.partitionBy(by, key).orderBy("rank")))
    out = hits.groupBy(by, key).agg((1 / F.min("rank")).alias("mrr"), F.sum(F.col("_k") / F.col("rank")).alias("_ap"), F.sum((F.col("rank") <= k).cast("int")).alias("_in"))
    out = total.crossJoin(_systems(ranked, systems, by)).join(out, [by, key], "left").fillna(0)
    return out.select(by, key, "mrr", (F.col("_ap") / F.col("_n")).alias("map"), (F.col("_in") / F.col("_n")).alias("recall"))


def complete(instances: DataFrame, systems: DataFrame, scores: DataFrame, *, key: str, by: str = "m") -> DataFrame:
    """A row for every instance and system; a missing answer scores 0."""
    return instances.select(key).distinct().crossJoin(F.broadcast(systems.select(by).distinct())).join(scores.select(by, key, "value"), [by, key], "left").fillna(0.0, ["value"])


def mean_rank(scores: DataFrame, *, by: str = "m", task: str = "task", value: str = "value") -> DataFrame:
    """Mean over tasks of the rank (ties share the smallest), from unrounded scores."""
    r = F.rank().over(Window.partitionBy(task).orderBy(F.desc(value)))
    return scores.withColumn("_r", r).groupBy(by).agg(F.round(F.avg("_r"), 6).alias("mean_rank"))


def lock_strategy(pilot: DataFrame, *, task: str = "task", strategy: str = "strategy", value: str = "value") -> DataFrame:
    """The strategy with the best mean over pilots of each task; ties go to the first by name."""
    means = pilot.groupBy(task, strategy).agg(F.round(F.avg(value), 6).alias("score"))
    first = F.row_number().over(Window.partitionBy(task).orderBy(F.desc("score"), strategy))
    return means.withColumn("_r", first).where("_r = 1").drop("_r")


def decompose(scores: DataFrame, *, keys: list[str], condition: str = "condition", value: str = "value") -> DataFrame:
    """Loop effect (agent with all context less the model alone) and retrieval effect (self-retrieving less all context)."""
    p = scores.groupBy(*keys).pivot(condition, ["llm_full", "agent_full", "agent_self"]).agg(F.avg(value))
    return p.select(*keys, *[F.round(c, 6).alias(c) for c in ("llm_full", "agent_full", "agent_self")], F.round(F.col("agent_full") - F.col("llm_full"), 6).alias("loop_effect"), F.round(F.col("agent_self") - F.col("agent_full"), 6).alias("retrieval_effect"))


def paired_bootstrap(diffs: DataFrame, *, keys: list[str], unit: str, value: str = "diff", rounds: int = 200) -> DataFrame:
    """(keys, mean, low, high): a 95 % interval of a mean difference.

    Every round gives each unit a weight of 0 to 3 from integer arithmetic on the unit and the round, close to
    Poisson(1), so the same units are drawn for all keys and the result does not depend on partitioning. [D]
    """
    draw = (F.col(unit) * 7919 + F.col("_b") * 104729 + (F.col(unit) % 97) * F.col("_b") * 31) % 10007
    weight = F.when(draw < 3681, 0).when(draw < 7363, 1).when(draw < 9204, 2).otherwise(3)
    rows = diffs.withColumn("_b", F.explode(F.sequence(F.lit(1), F.lit(rounds)))).withColumn("_w", weight)
    means = rows.groupBy(*keys, "_b").agg((F.sum(F.col("_w") * F.col(value)) / F.sum("_w")).alias("_mean"))
    ends = means.groupBy(*keys).agg(F.percentile("_mean", F.array(F.lit(0.025), F.lit(0.975))).alias("_q"))
    whole = diffs.groupBy(*keys).agg(F.avg(value).alias("_all"))
    return whole.join(ends, keys).select(*keys, F.round("_all", 6).alias("mean"), F.round(F.col("_q")[0], 6).alias("low"), F.round(F.col("_q")[1], 6).alias("high"))
