"""Low-dimensional features of behaviour: mean count per bin, mean change from bin to bin, first event."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from channelalign.operators.binning import bin_events, span


def average_count(binned: DataFrame, spans: DataFrame, over: str = "span") -> DataFrame:
    """channel, entity, aec: events per bin of the whole span, or per active bin."""
    sums = binned.groupBy("channel", "entity").agg(F.sum("cnt").alias("_sum"), F.count(F.lit(1)).alias("_active"))
    bins = F.col("n_bins") if over == "span" else F.col("_active")
    return sums.crossJoin(F.broadcast(spans.select("n_bins"))).select("channel", "entity", (F.col("_sum") / bins).alias("aec"))


def edge_delta(binned: DataFrame, spans: DataFrame, mode: str = "absolute", over: str = "span") -> DataFrame:
    """channel, entity, dec: mean difference of neighbouring bins' counts.

    Absolute differences by default; signed ones telescope to (last - first) / (bins - 1). Only stored cells are
    visited: a gap before a cell adds the previous count (down to zero) and the cell's own (up from zero); zeros
    before the first and after the last cell count where the span has them.
    """
    own = Window.partitionBy("channel", "entity").orderBy("bin")
    rows = binned.crossJoin(F.broadcast(spans.select("n_bins")))
    steps = F.greatest(F.col("n_bins") - 1, F.lit(1))
    if mode == "signed":
        last = F.sum(F.when(F.col("bin") == F.col("n_bins") - 1, F.col("cnt")).otherwise(0))
        first = F.sum(F.when(F.col("bin") == 0, F.col("cnt")).otherwise(0))
        out = rows.groupBy("channel", "entity").agg((last - first).alias("_d"), F.max("n_bins").alias("n_bins"), F.count(F.lit(1)).alias("_active"))
    elif mode == "absolute":
        lone = F.lag("bin").over(own).isNull()
        up = F.when(lone, F.when(F.col("bin") > 0, F.col("cnt")).otherwise(0)).when(F.col("bin") - F.lag("bin").over(own) == 1, F.abs(F.col("cnt") - F.lag("cnt").over(own))).otherwise(F.col("cnt") + F.lag("cnt").over(own))
        down = F.when(F.lead("bin").over(own).isNull() & (F.col("bin") < F.col("n_bins") - 1), F.col("cnt")).otherwise(0)
        out = rows.select("channel", "entity", "n_bins", (up + down).alias("_c")).groupBy("channel", "entity").agg(F.sum("_c").alias("_d"), F.max("n_bins").alias("n_bins"), F.count(F.lit(1)).alias("_active"))
    else:
        raise ValueError(f"no mode {mode}")
    return out.select("channel", "entity", (F.col("_d") / (steps if over == "span" else F.col("_active"))).alias("dec"))


def first_event(binned: DataFrame, spans: DataFrame, relative: bool = True) -> DataFrame:
    """channel, entity, ie: microseconds of the first event, from t0 unless relative is off. binned needs first_us."""
    first = binned.groupBy("channel", "entity").agg(F.min("first_us").alias("_first"))
    if not relative:
        return first.select("channel", "entity", F.col("_first").alias("ie"))
    return first.crossJoin(F.broadcast(spans.select("t0_us"))).select("channel", "entity", (F.col("_first") - F.col("t0_us")).alias("ie"))


def scaled(features: DataFrame, columns: list[str], over: str = "all") -> DataFrame:
    """channel, entity and f, an array of the columns, each divided by its maximum over all entities (or those of a channel); 0 where the maximum is 0."""
    most = [F.max(c).alias(f"_m_{c}") for c in columns]
    if over == "channel":
        wide = features.join(F.broadcast(features.groupBy("channel").agg(*most)), "channel")
    else:
        wide = features.crossJoin(F.broadcast(features.agg(*most)))
    return wide.select("channel", "entity", F.array(*[F.coalesce(F.col(c) / F.nullif(F.col(f"_m_{c}"), F.lit(0)), F.lit(0.0)).cast("double") for c in columns]).alias("f"))


def reduced_features(events: DataFrame, width_us: int, scale_over: str = "all", origin_us: int | None = None, role: str = "source") -> DataFrame:
    """channel, entity, f: the three measures, scaled by their maxima."""
    binned = bin_events(events, width_us, origin_us, role, with_first=True)
    spans = span(events, width_us, origin_us)
    own = Window.partitionBy("channel", "entity").orderBy("bin")
    # One window over the counts gives all three measures: a single shuffle beyond the binning.
    rows = binned.crossJoin(F.broadcast(spans.select("n_bins", "t0_us")))
    before, gap = F.lag("cnt").over(own), F.col("bin") - F.lag("bin").over(own)
    up = F.when(before.isNull(), F.when(F.col("bin") > 0, F.col("cnt")).otherwise(0)).when(gap == 1, F.abs(F.col("cnt") - before)).otherwise(F.col("cnt") + before)
    down = F.when(F.lead("bin").over(own).isNull() & (F.col("bin") < F.col("n_bins") - 1), F.col("cnt")).otherwise(0)
    raw = rows.select("channel", "entity", "cnt", "first_us", "n_bins", "t0_us", (up + down).alias("_c")).groupBy("channel", "entity").agg(
        (F.sum("cnt") / F.max("n_bins")).alias("aec"), (F.sum("_c") / F.greatest(F.max("n_bins") - 1, F.lit(1))).alias("dec"), (F.min("first_us") - F.max("t0_us")).cast("double").alias("ie")
    )
    return scaled(raw, ["aec", "dec", "ie"], scale_over)


def with_attributes(features: DataFrame, extra: DataFrame, columns: list[str]) -> DataFrame:
    """Further attributes of the entities, scaled likewise, behind the others; missing ones are 0."""
    more = scaled(extra, columns).withColumnRenamed("f", "_more")
    return features.join(more, ["channel", "entity"], "left").select("channel", "entity", F.concat("f", F.coalesce("_more", F.array(*[F.lit(0.0)] * len(columns)))).alias("f"))


def segment_features(planned: DataFrame, bins_a_segment: int) -> DataFrame:
    """segment, channel, entity, f: the three measures within each segment, whose bins are numbered from its start; scaled by the segment's maxima. The first event is told to a bin."""
    own = Window.partitionBy("segment", "channel", "entity").orderBy("bin")
    at = F.pmod(F.col("bin"), F.lit(bins_a_segment))
    before, gap = F.lag("cnt").over(own), F.col("bin") - F.lag("bin").over(own)
    up = F.when(before.isNull(), F.when(at > 0, F.col("cnt")).otherwise(0)).when(gap == 1, F.abs(F.col("cnt") - before)).otherwise(F.col("cnt") + before)
    down = F.when(F.lead("bin").over(own).isNull() & (at < bins_a_segment - 1), F.col("cnt")).otherwise(0)
    raw = planned.select("segment", "channel", "entity", "cnt", at.alias("_at"), (up + down).alias("_c")).groupBy("segment", "channel", "entity").agg(
        (F.sum("cnt") / bins_a_segment).alias("aec"), (F.sum("_c") / max(1, bins_a_segment - 1)).alias("dec"), F.min("_at").cast("double").alias("ie")
    )
    most = raw.groupBy("segment").agg(*[F.max(c).alias(f"_m_{c}") for c in ("aec", "dec", "ie")])
    wide = raw.join(F.broadcast(most), "segment")  # a row for each segment
    return wide.select("segment", "channel", "entity", F.array(*[F.coalesce(F.col(c) / F.nullif(F.col(f"_m_{c}"), F.lit(0)), F.lit(0.0)).cast("double") for c in ("aec", "dec", "ie")]).alias("f"))
