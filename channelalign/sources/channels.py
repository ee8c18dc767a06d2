"""Event channels from the given tables, files and streams.

Every adapter returns the event schema: channel, src, dst, us (microseconds since 1970 UTC), key.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from channelalign.sources.tables import load

EVENT_SCHEMA = T.StructType([
    T.StructField("channel", T.StringType()), T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()),
    T.StructField("us", T.LongType()), T.StructField("key", T.LongType()),
])


def micros(ts: Column | str) -> Column:
    """Microseconds since 1970 of a timestamp without zone, read as UTC whatever the session's zone is."""
    ntz = (F.col(ts) if isinstance(ts, str) else ts).cast("timestamp_ntz")
    day = F.datediff(ntz.cast("date"), F.lit("1970-01-01").cast("date")).cast("long")
    second = F.hour(ntz).cast("long") * 3600 + F.minute(ntz) * 60
    return (day * 86_400 + second) * 1_000_000 + (F.extract(F.lit("SECOND"), ntz) * 1_000_000).cast("long")


def events_channels(spark: SparkSession, sf_dir: str, channels: tuple[str, ...] | None = None) -> DataFrame:
    """The events table; a channel for each event type. The filter on the type reaches the scan."""
    e = load(spark, sf_dir, "events")
    if channels:
        e = e.where(F.col("event_type").isin(*channels))
    return e.select(F.col("event_type").alias("channel"), F.col("user_id").alias("src"), F.lit(None).cast("long").alias("dst"), micros("ts").alias("us"), F.col("event_id").alias("key"))


def orders_channel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as one channel of customers."""
    o = load(spark, sf_dir, "orders")
    return o.select(F.lit("orders").alias("channel"), F.col("o_custkey").alias("src"), F.lit(None).cast("long").alias("dst"), micros("o_orderdate").alias("us"), F.col("o_orderkey").alias("key"))


def lineitem_channels(spark: SparkSession, sf_dir: str, by: str = "l_returnflag") -> DataFrame:
    """Shipments as directed events from supplier to customer; a channel for each value of ``by``."""
    i, o = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return i.join(o, i["l_orderkey"] == o["o_orderkey"]).select(F.col(by).alias("channel"), F.col("l_suppkey").alias("src"), F.col("o_custkey").alias("dst"), micros("l_shipdate").alias("us"), F.col("l_orderkey").alias("key"))


def embedding_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The embeddings table as features of two channels, with its label."""
    e = load(spark, sf_dir, "embeddings")
    return e.select((F.col("vec_id") % 2).cast("string").alias("channel"), F.col("vec_id").alias("entity"), F.transform("embedding", lambda x: x.cast("double")).alias("f"), F.col("label").cast("int").alias("label"))


def read_csv(spark: SparkSession, path: str, **options) -> DataFrame:
    return spark.read.schema(EVENT_SCHEMA).options(header=True, **options).csv(path)


def read_json(spark: SparkSession, path: str, **options) -> DataFrame:
    return spark.read.schema(EVENT_SCHEMA).options(**options).json(path)


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Day files as a stream."""
    return spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).option("recursiveFileLookup", "true").parquet(path)


def rate_stream(spark: SparkSession, rows_per_second: int = 1000, entities: int = 100) -> DataFrame:
    """A synthetic stream for soak tests: two channels with the same activity."""
    r = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return r.select(F.when(F.col("value") % 2 == 0, "a").otherwise("b").alias("channel"), (F.shiftright("value", 1) % entities).alias("src"), F.lit(None).cast("long").alias("dst"), F.unix_micros("timestamp").alias("us"), F.col("value").alias("key"))


def split_usable(events: DataFrame, role: str = "source") -> tuple[DataFrame, DataFrame]:
    """(events with channel, time and the entities that the role needs, the others)."""
    need = {"source": ["src"], "target": ["dst"], "both": ["src", "dst"]}[role]
    good = F.lit(True)
    for c in ["channel", "us", *need]:
        good &= F.col(c).isNotNull()
    return events.where(good), events.where(~good)


def within(events: DataFrame, from_us: int | None = None, to_us: int | None = None, channels: tuple[str, ...] | None = None) -> DataFrame:
    """Half-open time range and channels."""
    if from_us is not None:
        events = events.where(F.col("us") >= from_us)
    if to_us is not None:
        events = events.where(F.col("us") < to_us)
    return events.where(F.col("channel").isin(*channels)) if channels else events
