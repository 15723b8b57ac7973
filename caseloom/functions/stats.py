"""Small exact statistics in expressions, and resampling that shuffles one row per replicate and partition."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T


def binom_two_sided(k: int, n: int, p: float = 0.5) -> float:
    """Probability of all outcomes that are no likelier than k of n."""
    logs = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log(1 - p) for i in range(n + 1)]
    return min(1.0, sum(math.exp(x) for x in logs if x <= logs[k] + 1e-9))


def incomplete_beta(a: float, b: float, x: float) -> float:
    """The regularized incomplete beta function by its continued fraction (modified Lentz)."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    if x > (a + 1) / (a + b + 2):
        return 1 - incomplete_beta(b, a, 1 - x)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log(1 - x)) / a
    tiny, c, d = 1e-300, 1.0, 1 / (1 - (a + b) * x / (a + 1))
    h = d
    for m in range(1, 300):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / (1 + num * d or tiny)
            c = 1 + num / c or tiny
            h *= c * d
        if abs(c * d - 1) < 1e-14:
            break
    return front * h


def t_two_sided(t: float, df: int) -> float:
    return incomplete_beta(df / 2, 0.5, df / (df + t * t))


@F.pandas_udf(T.DoubleType())
def binom_p(k: pd.Series, n: pd.Series) -> pd.Series:
    return pd.Series([binom_two_sided(int(a), int(b)) for a, b in zip(k, n, strict=True)])


def holm(tests: DataFrame, p: str = "p", key: str = "rater") -> DataFrame:
    """Step-down adjusted p values of a small family of tests."""
    w = Window.orderBy(p, key)
    m = F.count("*").over(Window.partitionBy())
    step = F.col(p) * (m - F.row_number().over(w) + 1)
    return tests.withColumn("_s", step).withColumn("adjusted", F.least(F.lit(1.0), F.max("_s").over(w.rowsBetween(Window.unboundedPreceding, 0)))).drop("_s")


def fleiss_kappa(calls: DataFrame, item: str = "record_id", called: str = "called") -> DataFrame:
    """Agreement of raters on items with two or more categories; every item has equally many calls."""
    cell = calls.groupBy(item, called).agg(F.count("*").alias("n"))
    per = cell.groupBy(item).agg(F.sum("n").alias("r"), F.sum(F.col("n") * (F.col("n") - 1)).alias("a")).select((F.col("a") / (F.col("r") * (F.col("r") - 1))).alias("agree"))
    share = cell.groupBy(called).agg(F.sum("n").alias("n")).select((F.col("n") / F.sum("n").over(Window.partitionBy())).alias("s"))
    both = per.agg(F.avg("agree").alias("po")).crossJoin(share.agg(F.sum(F.col("s") * F.col("s")).alias("pe")))
    return both.select(F.round((F.col("po") - F.col("pe")) / (1 - F.col("pe")), 6).alias("kappa"))


def jsd(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Jensen-Shannon divergence (base 2) of the distributions of a key in two frames."""
    share = lambda f, n: f.groupBy(key).count().select(key, (F.col("count") / F.sum("count").over(Window.partitionBy())).alias(n))
    j = share(a, "p").join(share(b, "q"), key, "full").fillna(0.0)
    mid = (F.col("p") + F.col("q")) / 2
    term = lambda x: F.when(F.col(x) > 0, F.col(x) * F.log2(F.col(x) / mid)).otherwise(0.0)
    return j.agg(F.round(F.sum((term("p") + term("q")) / 2), 6).alias("jsd"))


def spearman(rows: DataFrame, x: str, y: str) -> DataFrame:
    """Rank correlation with average ranks on ties, of a small frame."""
    def rank(c: str) -> Column:
        return F.rank().over(Window.orderBy(c)) + (F.count("*").over(Window.partitionBy(c)) - 1) / 2

    return rows.withColumns({"_x": rank(x), "_y": rank(y)}).agg(F.round(F.corr("_x", "_y"), 6).alias("rho"))


def bootstrap_ci(units: DataFrame, value: str, replicates: int = 1000, key: str = "id") -> DataFrame:
    """Percentile interval of a mean by Poisson weights from a hash of unit and replicate.

    Units times replicates exist only inside a partition; each sends one row per replicate.
    """
    u = (F.pmod(F.xxhash64(F.col(key), F.col("b")), F.lit(1_000_003)) + 0.5) / 1_000_003
    weight, total = F.lit(0), 0.0
    for k in range(8):
        total += math.exp(-1) / math.factorial(k)
        weight = weight + (u > total).cast("int")
    rows = units.withColumn("b", F.explode(F.sequence(F.lit(1), F.lit(replicates)))).withColumn("w", weight)
    means = rows.groupBy("b").agg((F.sum(F.col("w") * F.col(value)) / F.sum("w")).alias("m"))
    return means.agg(F.percentile("m", 0.025).alias("low"), F.percentile("m", 0.975).alias("high"))
