"""Statistics as column expressions and small plans: Wilson, normal and t tails, BH, Wilcoxon, ranks, bootstrap draws."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.functions.hashing import u32

Z95 = 1.959964


def r6(c) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6)


def wilson(k: Column, n: Column, z: float = Z95) -> tuple[Column, Column]:
    """Interval of a share; null for n = 0."""
    n = n.cast("double")
    p, d = F.try_divide(k.cast("double"), n), 1 + z * z / F.nullif(n, F.lit(0.0))
    mid = (p + z * z / (2 * n)) / d
    half = z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / d
    return mid - half, mid + half


def normal_upper(x: Column) -> Column:
    """P(Z > x), rational approximation of the error function, absolute error below 1.5e-7."""
    a = F.abs(x) / F.sqrt(F.lit(2.0))
    t = 1 / (1 + 0.3275911 * a)
    poly = t * (0.254829592 + t * (-0.284496736 + t * (1.421413741 + t * (-1.453152027 + t * 1.061405429))))
    half = 0.5 * poly * F.exp(-a * a)
    return F.when(x >= 0, half).otherwise(1 - half)


def t_upper(t: Column, df: Column) -> Column:
    """P(T > t) for integer degrees of freedom, by the finite trigonometric series."""
    theta = F.atan(t / F.sqrt(df.cast("double")))
    s, c2 = F.sin(theta), F.cos(theta) * F.cos(theta)
    odd = df % 2 == 1
    # factors of the series: term_k = term_(k-1) * c2 * (2k - 1 or 2k) / (2k or 2k + 1)
    n = F.when(odd, (df - 3) / 2).otherwise((df - 2) / 2).cast("int")
    steps = F.when(n >= 1, F.sequence(F.lit(1), F.greatest(n, F.lit(1)))).otherwise(F.array().cast("array<int>"))
    first = F.struct(F.lit(1.0).alias("term"), F.lit(1.0).alias("total"))

    def step(acc, k):
        k = k.cast("double")
        term = acc["term"] * c2 * F.when(odd, 2 * k / (2 * k + 1)).otherwise((2 * k - 1) / (2 * k))
        return F.struct(term.alias("term"), (acc["total"] + term).alias("total"))

    total = F.aggregate(steps, first, step)["total"]
    area = F.when(df == 1, 2 * theta / F.pi()).when(odd, 2 / F.pi() * (theta + s * F.cos(theta) * total)).otherwise(s * total)
    return (1 - area) / 2


def bh(df: DataFrame, p: str, family: list[str], out: str = "p_adj") -> DataFrame:
    """Benjamini-Hochberg within each family; null p-values are left out of the count."""
    by = Window.partitionBy(*family)
    m = F.count(p).over(by)
    rank = F.rank().over(by.orderBy(F.col(p).asc_nulls_last()))
    ties = F.count("*").over(by.orderBy(F.col(p).asc_nulls_last()).rangeBetween(Window.unboundedPreceding, Window.currentRow))
    raw = F.when(F.col(p).isNotNull(), F.col(p) * m / ties)
    df = df.withColumn("_raw", raw).withColumn("_rank", rank)
    low = F.min("_raw").over(Window.partitionBy(*family).orderBy(F.col(p).desc_nulls_first()).rangeBetween(Window.unboundedPreceding, Window.currentRow))
    return df.withColumn(out, F.when(F.col(p).isNotNull(), F.least(low, F.lit(1.0)))).drop("_raw", "_rank")


def pearson(x: str, y: str) -> Column:
    """Correlation of two columns without nulls; null where one of them doesn't vary."""
    varies = (F.min(x) < F.max(x)) & (F.min(y) < F.max(y))
    return F.when(varies, F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y)))


def average_rank(df: DataFrame, value: str, by: list[str], out: str) -> DataFrame:
    w = Window.partitionBy(*by)
    ties = F.count("*").over(Window.partitionBy(*by, value))
    return df.withColumn(out, F.rank().over(w.orderBy(value)) + (ties - 1) / 2.0)


def wilcoxon(df: DataFrame, d: str, by: list[str]) -> DataFrame:
    """One-sided signed-rank test (upper): n, w_plus, z, p.  Zeros dropped, average ranks, tie-corrected variance."""
    rows = df.where(F.col(d) != 0).withColumn("_abs", F.abs(F.col(d)))
    rows = average_rank(rows, "_abs", by, "_rank").withColumn("_ties", F.count("*").over(Window.partitionBy(*by, "_abs")))
    agg = rows.groupBy(*by).agg(F.count("*").alias("n"), F.sum(F.when(F.col(d) > 0, F.col("_rank")).otherwise(0.0)).alias("w_plus"),
        F.sum((F.col("_ties") * F.col("_ties") - 1) / 48.0).alias("_corr"))
    n = F.col("n").cast("double")
    z = F.try_divide(F.col("w_plus") - n * (n + 1) / 4, F.sqrt(n * (n + 1) * (2 * n + 1) / 24 - F.col("_corr")))
    return agg.withColumn("z", z).withColumn("p", normal_upper(F.col("z"))).drop("_corr")


def draws(spark, reps: int, n: DataFrame, seed: str) -> DataFrame:
    """(rep, unit): bootstrap draws of n units, made by the executors; ``n`` is one row (n), so it needs no job of its own."""
    grid = spark.range(reps).withColumnRenamed("id", "rep").crossJoin(F.broadcast(n))
    grid = grid.select("rep", "n", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("i"))
    return grid.select("rep", (u32(F.lit(seed), F.col("rep"), F.col("i")) % F.col("n")).alias("unit"))
