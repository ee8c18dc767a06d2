"""Event counts per entity and time bin, in long form: channel, entity, bin, cnt."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

HOUR_US = 3_600_000_000
DAY_US = 24 * HOUR_US


def with_role(events: DataFrame, role: str = "source") -> DataFrame:
    """events with a column ``entity``: the source, the target, or both (an event counts for either)."""
    if role == "source":
        return events.withColumn("entity", F.col("src"))
    if role == "target":
        return events.withColumn("entity", F.col("dst"))
    if role == "both":
        return events.withColumn("entity", F.explode(F.array("src", "dst")))
    raise ValueError(f"no role {role}")


def _bin(us: Column, origin: Column, width_us: int) -> Column:
    """The bin number; floors, so times before the origin have negative bins."""
    gone = us - origin
    return ((gone - F.pmod(gone, F.lit(width_us))) / F.lit(width_us)).cast("long")


def span(events: DataFrame, width_us: int, origin_us: int | None = None) -> DataFrame:
    """One row: t0_us (the first event of any channel unless pinned), last_us, n_bins. An empty frame gives nulls and 0 bins."""
    first = F.min("us") if origin_us is None else F.lit(origin_us).cast("long")
    row = events.agg(first.alias("t0_us"), F.max("us").alias("last_us"))
    return row.withColumn("n_bins", F.coalesce(_bin(F.col("last_us"), F.col("t0_us"), width_us) + 1, F.lit(0).cast("long")))


def bin_events(events: DataFrame, width_us: int, origin_us: int | None = None, role: str = "source", with_first: bool = False) -> DataFrame:
    """Counts of all channels in one pass: partial counts before the only shuffle. Rows without entity or time are left out.

    The origin is the first event of any channel, found once and joined as one broadcast row, or a pinned one, for
    streams and segments. with_first adds first_us, the bin's first event.
    """
    e = with_role(events, role).where(F.col("entity").isNotNull() & F.col("us").isNotNull())
    if origin_us is None:
        e = e.crossJoin(F.broadcast(events.agg(F.min("us").alias("_t0"))))
        origin = F.col("_t0")
    else:
        origin = F.lit(origin_us)
    counts = [F.count(F.lit(1)).alias("cnt")] + ([F.min("us").alias("first_us")] if with_first else [])
    return e.groupBy("channel", "entity", _bin(F.col("us"), origin, width_us).alias("bin")).agg(*counts)


def rebin(binned: DataFrame, factor: int) -> DataFrame:
    """Bins of a width ``factor`` times larger."""
    return binned.groupBy("channel", "entity", F.floor(F.col("bin") / factor).alias("bin")).agg(F.sum("cnt").alias("cnt"))


def to_vectors(binned: DataFrame) -> DataFrame:
    """One row per entity: bins and cnts (arrays in bin order), sq_norm, n_events."""
    packed = binned.groupBy("channel", "entity").agg(F.array_sort(F.collect_list(F.struct("bin", "cnt"))).alias("x"), F.sum(F.col("cnt") * F.col("cnt")).alias("sq_norm"), F.sum("cnt").alias("n_events"))
    return packed.select("channel", "entity", F.transform("x", lambda s: s["bin"]).alias("bins"), F.transform("x", lambda s: s["cnt"]).alias("cnts"), "sq_norm", "n_events")


def from_vectors(vectors: DataFrame) -> DataFrame:
    return vectors.select("channel", "entity", F.explode(F.arrays_zip("bins", "cnts")).alias("x")).select("channel", "entity", F.col("x.bins").alias("bin"), F.col("x.cnts").alias("cnt"))


def sparsity(binned: DataFrame, spans: DataFrame) -> DataFrame:
    """Per channel: entities, stored cells (nnz), bins, filled share of the whole matrix, events."""
    rows = binned.groupBy("channel").agg(F.countDistinct("entity").alias("n_entities"), F.count(F.lit(1)).alias("nnz"), F.sum("cnt").alias("n_events"))
    return rows.crossJoin(F.broadcast(spans.select("n_bins"))).withColumn("fill", F.col("nnz") / (F.col("n_entities") * F.col("n_bins")))


def active(binned: DataFrame, least_events: int) -> DataFrame:
    """Entities with at least so many events."""
    keep = binned.groupBy("channel", "entity").agg(F.sum("cnt").alias("_n")).where(F.col("_n") >= least_events).select("channel", "entity")
    return binned.join(keep, ["channel", "entity"], "left_semi")
