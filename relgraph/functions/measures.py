"""Accuracy and cost measures over runs (method, pair_id, k, rep, r_hat, ...)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BY = ["method", "k"]


def required_samples(eps: Column, lam: Column, r: Column) -> Column:
    """Samples after which plain sampling errs by a share of more than eps with a chance of at most lam."""
    return F.ceil(3 / (eps * eps * r) * F.log(2 / lam)).cast("long")


def binomial_variance(r: Column, k: Column) -> Column:
    return r * (1 - r) / k


def pair_variance(runs: DataFrame) -> DataFrame:
    """(method, k, pair_id, v, r): spread and mean of a pair's repeats."""
    return runs.groupBy(*BY, "pair_id").agg(F.var_samp("r_hat").alias("v"), F.avg("r_hat").alias("r"))


def dispersion(runs: DataFrame) -> DataFrame:
    """(method, k, pairs, v_k, r_k, rho): mean variance, mean reliability and their ratio, null where nothing is reached."""
    mean = pair_variance(runs).groupBy(*BY).agg(F.count("*").alias("pairs"), F.avg("v").alias("v_k"), F.avg("r").alias("r_k"))
    return mean.withColumn("rho", F.when(F.col("r_k") > 0, F.col("v_k") / F.when(F.col("r_k") > 0, F.col("r_k")).otherwise(1.0)))


def relative_error(runs: DataFrame, reference: DataFrame) -> DataFrame:
    """(method, k, re, skipped): mean deviation in per cent from the reference (pair_id, ref); pairs whose reference is 0 are skipped."""
    mean = runs.groupBy(*BY, "pair_id").agg(F.avg("r_hat").alias("r"))
    both = mean.join(reference, "pair_id")
    off = F.when(F.col("ref") > 0, F.abs(F.col("r") - F.col("ref")) / F.when(F.col("ref") > 0, F.col("ref")).otherwise(1.0) * 100)
    return both.groupBy(*BY).agg(F.avg(off).alias("re"), F.count_if(F.col("ref") <= 0).alias("skipped"))


def pairwise_deviation(errors: DataFrame, reference: str | None = None) -> DataFrame:
    """(k, d): mean absolute difference of relative errors over ordered pairs of methods; a named reference method is left out.

    The rows number methods, so the join of the rows with themselves is small.
    """
    rows = errors if reference is None else errors.where(F.col("method") != reference)
    a = rows.select("k", F.col("method").alias("a"), F.col("re").alias("x"))
    b = rows.select("k", F.col("method").alias("b"), F.col("re").alias("y"))
    return a.join(b, "k").where("a <> b").groupBy("k").agg(F.avg(F.abs(F.col("x") - F.col("y"))).alias("d"))


def coverage(runs: DataFrame, exact: DataFrame, eps: float) -> DataFrame:
    """(method, k, share): share of runs within a relative eps of the exact value (pair_id, exact)."""
    both = runs.join(exact, "pair_id")
    return both.groupBy(*BY).agg(F.avg((F.abs(F.col("r_hat") - F.col("exact")) <= eps * F.col("exact")).cast("double")).alias("share"))


def cost(runs: DataFrame) -> DataFrame:
    """(method, k, probes, k_used, depth): mean cost of a run."""
    return runs.groupBy(*BY).agg(F.avg("probes").alias("probes"), F.avg("k_used").alias("k_used"), F.max("depth").alias("depth"))
