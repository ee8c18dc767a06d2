"""Two channels with a known alignment, derived from the given tables by integer arithmetic.

Some entities are in one channel only, one in ten is split in two in channel b, each channel lacks a tenth of the
events and the times of channel b are shifted by a bounded, deterministic jitter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from channelalign.sources.channels import micros
from channelalign.sources.tables import load

DAY_US = 86_400_000_000


def _alias(entity: Column, size: Column, split: Column) -> Column:
    return 1_000_000 + 2 * ((entity * 37 + 11) % size) + F.when(entity % 10 == 0, split).otherwise(0)


def _twin(rows: DataFrame, size: DataFrame, shift: Column, split: Column) -> tuple[DataFrame, DataFrame]:
    """rows: entity, us, key (noise source). size: one row, n."""
    a = rows.where((F.col("key") % 10 != 9) & (F.col("entity") % 7 != 5)).select(F.lit("a").alias("channel"), F.col("entity").alias("src"), F.lit(None).cast("long").alias("dst"), "us", "key")
    renamed = rows.where((F.col("key") % 10 != 4) & (F.col("entity") % 7 != 3)).crossJoin(F.broadcast(size)).select("entity", "key", F.col("us") + shift, _alias(F.col("entity"), F.col("n"), split).alias("alias"))
    renamed = renamed.toDF("entity", "key", "us", "alias")
    b = renamed.select(F.lit("b").alias("channel"), F.col("alias").alias("src"), F.lit(None).cast("long").alias("dst"), "us", "key")
    truth = renamed.where(F.col("entity") % 7 != 5).select(F.col("entity").alias("u"), F.col("alias").alias("v")).distinct()
    return a.unionByName(b), truth


def planted_events(spark: SparkSession, sf_dir: str, jitter_s: int = 1, profile: bool = False, users: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(events, truth) from the events table. profile: users differ in rate and start. users: only ids below."""
    e = load(spark, sf_dir, "events").select(F.col("user_id").alias("entity"), micros("ts").alias("us"), F.col("event_id").alias("key"))
    size = e.agg((F.max("entity") + 1).alias("n"))
    if users is not None:
        e = e.where(F.col("entity") < users)
    if profile:
        start = F.lit(1_704_067_200_000_000) + (F.col("entity") * 13 % 20) * DAY_US  # 2024-01-01
        e = e.where((F.floor(F.col("key") / 10) % (1 + F.col("entity") % 5) == 0) & (F.col("us") >= start))
    return _twin(e, size, (F.col("key") * 7919 % (2 * jitter_s + 1) - jitter_s) * 1_000_000, F.col("key") % 2)


def planted_lineitem(spark: SparkSession, sf_dir: str, entity: str = "l_suppkey", below: int | None = None, share: float | None = None) -> tuple[DataFrame, DataFrame]:
    """(events, truth) from shipments: suppliers or parts as entities, one day of jitter for a fifth of channel b. below: only ids below; share: only that share of the table's ids, from the least."""
    i = load(spark, sf_dir, "lineitem").select(F.col(entity).alias("entity"), micros("l_shipdate").alias("us"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("key"))
    table, key = {"l_suppkey": ("supplier", "s_suppkey"), "l_partkey": ("part", "p_partkey")}[entity]
    size = load(spark, sf_dir, table).agg((F.count(F.lit(1)) * 10 + 1).alias("n"))
    if share is not None:
        i = i.crossJoin(F.broadcast(size)).where(F.col("entity") <= share * ((F.col("n") - 1) / 10)).drop("n")
    if below is not None:
        i = i.where(F.col("entity") < below)
    return _twin(i, size, F.when(F.col("key") % 5 == 0, F.lit(DAY_US)).otherwise(F.lit(0)), F.col("key") % 2)
