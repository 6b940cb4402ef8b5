"""Analytic means, variances and errors of the estimates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import oue


def ratio_mean(fx, fy):
    """First-order mean of the ratio of two estimates."""
    return fx / fy


def length_prob_mean(freqs: DataFrame) -> DataFrame:
    """(len, p): what the estimated distribution of lengths is on average, from true counts (len, f)."""
    return freqs.select("len", (F.col("f") / F.sum("f").over(Window.partitionBy())).alias("p"))


def ratio_variance(fx, fy, vx, vy, cov=0.0):
    """First-order variance of the ratio of two estimates; numbers or columns."""
    return (fx * fx) / (fy * fy) * (vx / (fx * fx) - 2 * cov / (fx * fy) + vy / (fy * fy))


def length_error(freqs: DataFrame, eps1: float, denom_terms: str | int = 8) -> DataFrame:
    """(error) of the length distribution from true counts (len, f). The last term's constant is 8 as printed; "derived" takes the number of lengths."""
    total = freqs.agg(F.sum("f").alias("n"), F.count("*").alias("d"))
    t = freqs.where("f > 0").crossJoin(F.broadcast(total))
    sigma2 = F.col("n") * F.lit(oue.variance(1.0, eps1))
    last = F.col("d") if denom_terms == "derived" else F.lit(denom_terms)
    f, n = F.col("f").cast("double"), F.col("n").cast("double")
    return t.select(((f / n) * (f / n) * (sigma2 / (f * f) - 2 * sigma2 / (f * n) + last * sigma2 / (n * n))).alias("e")).agg(F.sum("e").alias("error"))


def transition_noise(freqs: DataFrame, n: Column | int, eps2: float, l_k: int) -> DataFrame:
    """(src, dst, noise): variance of each transition's probability from true counts (src, dst, f) and n reports; the denominator sums the estimates of its row."""
    v = F.lit(oue.variance(1.0, eps2 / l_k)) * (n if isinstance(n, Column) else F.lit(n))
    row = Window.partitionBy("src")
    t = freqs.where("f > 0").select("src", "dst", F.col("f").cast("double").alias("f"), F.sum("f").over(row).cast("double").alias("fy"), F.count("*").over(row).alias("m"))
    # the numerator is one of the summands, so their covariance is its variance
    return t.select("src", "dst", ratio_variance(F.col("f"), F.col("fy"), v, F.col("m") * v, v).alias("noise"))


def transition_error_curve(freqs: DataFrame, lengths: DataFrame, users: int, eps2: float, ks: list[float]) -> DataFrame:
    """(k, l_k, noise, bias, error) for each quantile k: noise of all transitions at eps2 / l_k, and (1 - k)^2 p^2 for what is left out.

    Needs true counts, so it is a check for the laboratory. lengths: (len, f).
    """
    spark = freqs.sparkSession
    run = lengths.withColumn("c", F.sum("f").over(Window.orderBy("len")) / F.sum("f").over(Window.partitionBy()))
    k = spark.createDataFrame([(float(x),) for x in ks], "k double")
    lk = k.join(F.broadcast(run), F.col("c") >= F.col("k") - 1e-12).groupBy("k").agg(F.min("len").alias("l_k"))
    row = Window.partitionBy("src")
    t = freqs.where("f > 0").withColumn("fy", F.sum("f").over(row).cast("double")).withColumn("m", F.count("*").over(row))
    v = oue.variance_col(F.lit(float(users)) * F.col("l_k"), F.lit(eps2) / F.col("l_k"))
    j = t.crossJoin(F.broadcast(lk)).withColumn("v", v)
    f = F.col("f").cast("double")
    noise = ratio_variance(f, F.col("fy"), F.col("v"), F.col("m") * F.col("v"), F.col("v"))
    bias = (1 - F.col("k")) * (1 - F.col("k")) * (f / F.col("fy")) * (f / F.col("fy"))
    out = j.select("k", "l_k", noise.alias("a"), bias.alias("b")).groupBy("k", "l_k").agg(F.sum("a").alias("noise"), F.sum("b").alias("bias"))
    return out.withColumn("error", F.col("noise") + F.col("bias"))


def best_quantile(curve: DataFrame) -> DataFrame:
    return curve.agg(F.min_by("k", F.struct("error", "k")).alias("k"))
