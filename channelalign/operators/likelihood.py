"""Likelihood of a match: Rayleigh fits of best similarities with and without a partner, and the log ratio of their densities."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def training_sample(binned: DataFrame, left: str, right: str, left_fraction: float = 1.0, right_fraction: float = 1.0, seed: int = 0) -> DataFrame:
    """The rows of sampled entities: integer arithmetic on the entity decides (any SQL engine repeats it), so an entity is in or out as a whole, on every retry. Sampling one side only keeps the partners of what is sampled."""
    chance = F.pmod(F.pmod(F.col("entity") * 7919 + (seed + 1) * 104_729, F.lit(1_000_003)) * 31_337 + 613, F.lit(1_000_003)) / 1_000_003
    return binned.where(F.when(F.col("channel") == left, chance < left_fraction).when(F.col("channel") == right, chance < right_fraction).otherwise(False))


def entities(binned: DataFrame, channel: str, name: str, keys: tuple[str, ...] = ()) -> DataFrame:
    return binned.where(F.col("channel") == channel).select(*keys, F.col("entity").alias(name)).distinct()


def h1_maxima(pairs: DataFrame, u_ids: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys, u, s: the greatest similarity of each u; 0 without any."""
    best = pairs.groupBy(*keys, "u").agg(F.max("sim").alias("s"))
    return u_ids.join(best, [*keys, "u"], "left").select(*keys, "u", F.coalesce("s", F.lit(0.0)).alias("s"))


def numbered(ids: DataFrame, column: str, keys: tuple[str, ...] = (), buckets: int = 64) -> DataFrame:
    """ids with their place (0, 1, ...) in the order of (id mod buckets, id) as ``place`` and their number as ``total``, without a window over all of them."""
    b = F.pmod(F.col(column), F.lit(buckets))
    counts = ids.groupBy(*keys, b.alias("_b")).agg(F.count(F.lit(1)).alias("_n"))
    every = Window.partitionBy(*keys)
    starts = counts.select(*keys, "_b", (F.sum("_n").over(every.orderBy("_b")) - F.col("_n")).alias("_start"), F.sum("_n").over(every).alias("total"))
    own = ids.withColumn("_b", b).withColumn("_r", F.row_number().over(Window.partitionBy(*keys, "_b").orderBy(column)) - 1)
    return own.join(starts, [*keys, "_b"]).select(*keys, column, (F.col("_start") + F.col("_r")).alias("place"), "total")


def draw(u: Column, j: Column, total: Column, seed: int) -> Column:
    """A place for the j-th draw of u: integer arithmetic that any SQL engine repeats."""
    return ((u * 7919 + (j + 1) * 104_729 + seed * 15_485_863) % 1_000_003 * 31_337 + u * 613 + j * 86_028_121) % total


def h0_maxima(pairs: DataFrame | Callable[[DataFrame], DataFrame], u_ids: DataFrame, v_ids: DataFrame, m: int | str = 10, seed: int = 0, scope: str = "row", axis: str = "u", keys: tuple[str, ...] = ()) -> DataFrame:
    """keys, u, s: the greatest of a uniform sample of similarities that hardly holds a true partner.

    scope row draws m entities of the other side for each u (with replacement); those without a common bin count
    as 0, as leaving them out would raise the fit. scope pool draws (u, v) pairs from all: a u that is drawn
    itself, too. m "matched" takes the runner-up of each row instead: the maximum over as many candidates as the
    row's best, which is left out. axis v swaps the sides. Rows: m per u; no grid of all pairs is made. pairs: all
    similarities or, for draws, a function that adds ``sim`` to rows with keys, u and v.
    """
    if axis == "v":
        def turn(rows: DataFrame) -> DataFrame:
            return rows.withColumnsRenamed({"u": "_v", "v": "u"}).withColumnRenamed("_v", "v")

        swapped = (lambda asked: turn(pairs(turn(asked)))) if callable(pairs) else turn(pairs)
        out = h0_maxima(swapped, v_ids.withColumnRenamed("v", "u"), u_ids.withColumnRenamed("u", "v"), m, seed, scope, "u", keys)
        return out.withColumnRenamed("u", "v")
    if m == "matched":
        second = pairs.withColumn("_r", F.row_number().over(Window.partitionBy(*keys, "u").orderBy(F.col("sim").desc(), "v"))).where("_r = 2").select(*keys, "u", F.col("sim").alias("s"))
        return u_ids.join(second, [*keys, "u"], "left").select(*keys, "u", F.coalesce("s", F.lit(0.0)).alias("s"))
    vs = numbered(v_ids, "v", keys)
    totals = vs.groupBy(*keys).agg(F.max("total").alias("total"))
    spread = u_ids.join(totals, list(keys)) if keys else u_ids.crossJoin(F.broadcast(totals))
    draws = spread.withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(int(m) - 1).cast("long"))))
    draws = draws.withColumn("place", draw(F.col("u"), F.col("j"), F.col("total"), seed)).drop("total")
    if scope == "pool":
        us = numbered(u_ids, "u", keys).select(*keys, F.col("u").alias("_u"), F.col("place").alias("_up"), F.col("total").alias("_ut"))
        ut = us.groupBy(*keys).agg(F.max("_ut").alias("_t"))
        draws = (draws.join(ut, list(keys)) if keys else draws.crossJoin(F.broadcast(ut))).withColumn("_up", draw(F.col("u"), F.col("j"), F.col("_t"), seed + 1)).drop("_t")
        draws = draws.withColumnRenamed("u", "_owner").join(us.drop("_ut"), [*keys, "_up"]).select(*keys, "_owner", F.col("_u").alias("u"), "place")
    elif scope != "row":
        raise ValueError(f"no scope {scope}")
    else:
        draws = draws.withColumn("_owner", F.col("u"))
    met = draws.join(vs.select(*keys, "v", "place"), [*keys, "place"])
    met = pairs(met) if callable(pairs) else met.join(pairs.select(*keys, "u", "v", "sim"), [*keys, "u", "v"], "left")
    return met.groupBy(*keys, F.col("_owner").alias("u")).agg(F.max(F.coalesce("sim", F.lit(0.0))).alias("s"))


def fit_rayleigh(maxima: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys, sigma, n: the maximum-likelihood fit in closed form."""
    return maxima.groupBy(*keys).agg(F.sqrt(F.sum(F.col("s") * F.col("s")) / (2 * F.count("s"))).alias("sigma"), F.count("s").alias("n"))


def fit_model(h1: DataFrame, h0: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys, sigma1, sigma0, n1, n0. A fit of 0 (nothing alike at all) is null: such a model scores nothing."""
    one = fit_rayleigh(h1, keys).select(*keys, F.nullif("sigma", F.lit(0.0)).alias("sigma1"), F.col("n").alias("n1"))
    none = fit_rayleigh(h0, keys).select(*keys, F.nullif("sigma", F.lit(0.0)).alias("sigma0"), F.col("n").alias("n0"))
    return (one.join(none, list(keys)) if keys else one.crossJoin(none)).select(*keys, "sigma1", "sigma0", "n1", "n0")


def rayleigh_pdf(s: Column, sigma: Column) -> Column:
    return s / (sigma * sigma) * F.exp(-s * s / (2 * sigma * sigma))


def rayleigh_cdf(s: Column, sigma: Column) -> Column:
    return 1 - F.exp(-s * s / (2 * sigma * sigma))


def ks_rayleigh(maxima: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys, ks: the greatest distance of the sample's distribution from the fitted one."""
    fitted = fit_rayleigh(maxima, keys)
    steps = maxima.groupBy(*keys, "s").agg(F.count(F.lit(1)).alias("_c"))
    # Running counts by way of 1024 buckets of the value: no window holds more than a bucket, or the buckets' totals.
    steps = steps.withColumn("_b", F.floor(F.col("s") * 1024))
    held = steps.groupBy(*keys, "_b").agg(F.sum("_c").alias("_h"))
    every = Window.partitionBy(*keys) if keys else Window.partitionBy(F.lit(0))  # over at most 1025 rows
    held = held.select(*keys, "_b", (F.sum("_h").over(every.orderBy("_b")) - F.col("_h")).alias("_before"), F.sum("_h").over(every).alias("_n"))
    upto = Window.partitionBy(*keys, "_b").orderBy("s").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    steps = steps.withColumn("_k", F.sum("_c").over(upto)).join(held, [*keys, "_b"]).withColumn("_k", F.col("_k") + F.col("_before"))
    at = (steps.join(fitted, list(keys)) if keys else steps.crossJoin(F.broadcast(fitted))).withColumn("_f", rayleigh_cdf(F.col("s"), F.nullif("sigma", F.lit(0.0))))
    far = F.greatest(F.abs(F.col("_k") / F.col("_n") - F.col("_f")), F.abs((F.col("_k") - F.col("_c")) / F.col("_n") - F.col("_f")))
    return at.groupBy(*keys).agg(F.max(far).alias("ks"))


def overlap(sigma1: Column, sigma0: Column) -> Column:
    """The common area of both densities: 1 if they are equal; large means weak features."""
    big, small = F.greatest(sigma1, sigma0), F.least(sigma1, sigma0)
    squared = 4 * F.ln(big / small) / (1 / (small * small) - 1 / (big * big))
    return F.when(sigma1 == sigma0, F.lit(1.0)).otherwise(1 - F.exp(-squared / (2 * big * big)) + F.exp(-squared / (2 * small * small)))


def log_ratio(s: Column, sigma1: Column, sigma0: Column) -> Column:
    return 2 * F.ln(sigma0 / sigma1) + s * s / 2 * (1 / (sigma0 * sigma0) - 1 / (sigma1 * sigma1))


def score(pairs: DataFrame, model: DataFrame, form: str = "ratio", keys: tuple[str, ...] = (), prior: float = 0.5) -> DataFrame:
    """pairs with ``score``: the log ratio of the densities (finite at 0), the log density of a match alone, or the log posterior of a match."""
    wide = pairs.join(F.broadcast(model), list(keys)) if keys else pairs.crossJoin(F.broadcast(model))
    s, s1, s0 = F.col("sim"), F.col("sigma1"), F.col("sigma0")
    ratio = log_ratio(s, s1, s0)
    by = {
        "ratio": ratio,
        "log_p1": F.ln(F.greatest(rayleigh_pdf(s, s1), F.lit(1e-300))),
        "posterior": -F.log1p(F.exp(-(ratio + F.lit(math.log(prior / (1 - prior)))))),
    }[form]
    return wide.select(*pairs.columns, by.alias("score"))


def distribution(h1: DataFrame, h0: DataFrame, n_bins: int = 20, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys, side (H1, H0), bucket, low, observed (density), fitted (density at the middle): the histogram of both maxima on 0..1."""
    def side(name: str, maxima: DataFrame) -> DataFrame:
        fitted = fit_rayleigh(maxima, keys)
        counts = maxima.groupBy(*keys, F.least(F.floor(F.col("s") * n_bins), F.lit(n_bins - 1)).cast("long").alias("bucket")).agg(F.count(F.lit(1)).alias("c"))
        middle = (F.col("bucket") + 0.5) / n_bins
        return (counts.join(fitted, list(keys)) if keys else counts.crossJoin(F.broadcast(fitted))).select(*keys, F.lit(name).alias("side"), "bucket", (F.col("bucket") / n_bins).alias("low"), (F.col("c") * n_bins / F.col("n")).alias("observed"), rayleigh_pdf(middle, F.col("sigma")).alias("fitted"))

    return side("H1", h1).unionByName(side("H0", h0))


def shuffled_null(binned: DataFrame, channel: str, spans: DataFrame, seed: int = 0) -> DataFrame:
    """binned with the bins of one channel moved by an offset of each entity's own, around the span: activity without any common time. Maxima computed on it calibrate what the same number of candidates reaches by chance."""
    moved = F.pmod(F.col("bin") + F.pmod(F.xxhash64("entity", F.lit(seed)), F.col("n_bins")), F.col("n_bins"))
    rows = binned.crossJoin(F.broadcast(spans.select("n_bins")))
    return rows.withColumn("bin", F.when(F.col("channel") == channel, moved).otherwise(F.col("bin"))).groupBy(*[c for c in binned.columns if c != "cnt"]).agg(F.sum("cnt").alias("cnt")).select(*binned.columns)
