"""Alignment over time segments: scores of a pair add up from segment to segment."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from channelalign.operators import likelihood, matching, similarity
from channelalign.operators.binning import DAY_US
from channelalign.sources.shared import written
from channelalign.sources.state import StateStore

STATE = ("u", "v", "score", "n_segments", "last_segment")


def segment_of_bin(width_us: int, every_days: int, origin_us: int = 0) -> Column:
    """The number of the segment of so many days that a bin (counted from the pinned origin) lies in."""
    per = every_days * DAY_US // width_us
    if per * width_us != every_days * DAY_US:
        raise ValueError("bins must divide segments")
    return F.floor(F.col("bin") / per).cast("long")


def month_of_day_bin(origin_us: int) -> Column:
    """Months since January 1970 of a bin of one day from an origin at midnight UTC."""
    date = F.date_add(F.lit("1970-01-01").cast("date"), (F.col("bin") + origin_us // DAY_US).cast("int"))
    return ((F.year(date) - 1970) * 12 + F.month(date) - 1).cast("long")


def plan(binned: DataFrame, segment: Column) -> DataFrame:
    """binned with its segment. Every later step takes the segment as a key, so segments never mix."""
    return binned.withColumn("segment", segment)


def train(binned: DataFrame, left: str, right: str, m: int | str = 10, left_fraction: float = 1.0, right_fraction: float = 1.0, seed: int = 0, scope: str = "row", pairs: DataFrame | None = None) -> DataFrame:
    """One model per segment: segment, sigma1, sigma0, n1, n0. Trained on pairs without regard to clusters.

    pairs: all similarities of the segments, if they are at hand and nothing is sampled. A sample of the left
    entities keeps all their partners; the products of the training join shrink with the fraction.
    """
    keys = ("segment",)
    sample = binned if left_fraction >= 1 and right_fraction >= 1 else likelihood.training_sample(binned, left, right, left_fraction, right_fraction, seed)
    if pairs is None or sample is not binned:
        pairs = written(similarity.pairwise_cosine(sample, left, right, keys=keys), "training")
    us, vs = likelihood.entities(sample, left, "u", keys), likelihood.entities(sample, right, "v", keys)
    h1 = likelihood.h1_maxima(pairs, us, keys)
    h0 = likelihood.h0_maxima(pairs, us, vs, m, seed, scope, keys=keys)
    return likelihood.fit_model(h1, h0, keys)


#: The share of left entities that a model is trained on where the scored pairs are not all pairs (clusters, a least similarity).
TRAINED = 0.1


def score_segments(
    binned: DataFrame, left: str, right: str, labels: DataFrame | None = None, form: str = "ratio", model: DataFrame | None = None, absent: str = "neutral", pairs: DataFrame | None = None,
    min_sim: float | None = None, prune: bool = False, salts: int = 1, left_fraction: float | None = None, **how,
) -> DataFrame:
    """segment, u, v, sim, score of every pair of every segment in one plan.

    Pairs are computed once and written: the model and the scores both read them. With labels (with or without a
    segment of their own) or min_sim they are not all pairs; the model is then trained on a sample of the left
    entities (left_fraction, TRAINED by default) against all right ones, so no join of all pairs is made. Without
    either, left_fraction is 1 and nothing is joined twice. min_sim leaves pairs below it unscored.

    absent active_zero: pairs that were seen in some segment get the score of similarity 0 for every other segment
    in which both entities are active.
    """
    keys = ("segment",)
    whole = labels is None and min_sim is None
    if pairs is None:
        pairs = written(similarity.pairwise_cosine(binned, left, right, labels=labels, keys=keys, min_sim=min_sim, prune=prune and min_sim is not None, salts=salts), "pairs")
    if model is None:
        model = train(binned, left, right, pairs=pairs if whole else None, left_fraction=left_fraction or (1.0 if whole else TRAINED), **how)
    scored = likelihood.score(pairs.select("segment", "u", "v", "sim"), model, form, keys)
    if absent == "neutral":
        return scored
    if absent != "active_zero":
        raise ValueError(f"no way {absent}")
    known = pairs.select("u", "v").distinct()
    us, vs = likelihood.entities(binned, left, "u", keys), likelihood.entities(binned, right, "v", keys)
    silent = known.join(us, "u").join(vs, ["segment", "v"]).join(pairs.select("segment", "u", "v"), ["segment", "u", "v"], "left_anti")
    zeros = likelihood.score(silent.select("segment", "u", "v", F.lit(0.0).alias("sim")), model, form, keys)
    return scored.unionByName(zeros)


def accumulate(scored: DataFrame, state: DataFrame | None = None, keep_floor: float | None = None, keep_top: int | None = None) -> DataFrame:
    """State after these scores: sums of scores per pair, with those of an earlier state. Optional pruning drops pairs below a floor or outside of each u's top; it loses what they might have become."""
    rows = scored.select("u", "v", "score", F.lit(1).cast("long").alias("n_segments"), F.col("segment").alias("last_segment"))
    if state is not None:
        rows = rows.unionByName(state.select(*STATE))
    out = rows.groupBy("u", "v").agg(F.sum("score").alias("score"), F.sum("n_segments").alias("n_segments"), F.max("last_segment").alias("last_segment"))
    if keep_floor is not None:
        out = out.where(F.col("score") >= keep_floor)
    if keep_top is not None:
        out = out.withColumn("_r", F.row_number().over(Window.partitionBy("u").orderBy(F.col("score").desc(), "v"))).where(F.col("_r") <= keep_top).drop("_r")
    return out


def retract(state: DataFrame, scored: DataFrame) -> DataFrame:
    """State without the scores of a segment that is to be scored again."""
    gone = scored.select("u", "v", (-F.col("score")).alias("score"), F.lit(-1).cast("long").alias("n_segments"), F.lit(None).cast("long").alias("last_segment"))
    rows = state.select(*STATE).unionByName(gone)
    return rows.groupBy("u", "v").agg(F.sum("score").alias("score"), F.sum("n_segments").alias("n_segments"), F.max("last_segment").alias("last_segment")).where("n_segments > 0")


def trajectory(scored: DataFrame) -> DataFrame:
    """segment, u, v, score, total: the running sum of a pair's scores."""
    upto = Window.partitionBy("u", "v").orderBy("segment").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return scored.select("segment", "u", "v", "score", F.sum("score").over(upto).alias("total"))


def matches(state: DataFrame, theta: float, rule: str = "best", how: str = "intersect", m: int = 1) -> DataFrame:
    """Reliable matches: pairs of at least this score that both directions select."""
    return matching.reconcile(state, how=how, rule=rule, theta=theta, m=m, score="score")


def run_all(binned: DataFrame, left: str, right: str, segments: list[int], store, **how) -> DataFrame:
    """The loop: each segment is run by itself and its scores join the stored ones of the runs before.

    store: a SegmentStore (writes the segment's scores only) or a StateStore (writes the whole state) of
    channelalign.sources.state. A segment that the store already has is skipped, so a run that broke off goes on
    where it stopped and none counts twice. Plans stay short, since the state is read anew.
    """
    for segment in segments:
        if store.has(segment):
            continue
        now = score_segments(binned.where(F.col("segment") == segment), left, right, **how)
        store.commit(segment, accumulate(now, store.read()) if isinstance(store, StateStore) else now)
    return store.read()
