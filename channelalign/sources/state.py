"""Day files, and state: versions of the whole, or the scores of every segment beside a snapshot. What is complete is told by Spark's mark of success."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from channelalign.sources.channels import EVENT_SCHEMA

_VERSION = re.compile(r"version-(\d+)-of-(-?\d+)")
_SCORES = re.compile(r"scores-(\d+)-of-(-?\d+)-at-(-?\d+)")
_SNAPSHOT = re.compile(r"snapshot-(\d+)")
BINS_SCHEMA = "channel string, entity long, bin long, cnt long, segment long, batch long"
STATE_SCHEMA = "u long, v long, score double, n_segments long, last_segment long"


def write_days(events: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Day files: one folder per UTC day, so a set of days is read by partition pruning. Rows of a day meet before they are written; AQE splits a day that is too large for one file."""
    day = F.date_add(F.lit("1970-01-01").cast("date"), F.floor(F.col("us") / 86_400_000_000).cast("int"))
    events.withColumn("day", day).repartition("day").sortWithinPartitions("day", "channel", "us").write.mode(mode).partitionBy("day").parquet(path)


def read_days(spark: SparkSession, path: str, from_day: str | None = None, to_day: str | None = None) -> DataFrame:
    """Events of the days from ``from_day`` up to, not including, ``to_day``."""
    frame = spark.read.schema(T.StructType([*EVENT_SCHEMA.fields, T.StructField("day", T.DateType())])).parquet(path)
    if from_day:
        frame = frame.where(F.col("day") >= F.lit(from_day).cast("date"))
    if to_day:
        frame = frame.where(F.col("day") < F.lit(to_day).cast("date"))
    return frame


class _Folder:
    """A folder of complete results, through Spark's own file systems only."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        jvm = spark.sparkContext._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _complete(self, pattern: re.Pattern) -> list[tuple]:
        """(the pattern's numbers, name) of the complete folders, in order: Spark writes the mark of success last."""
        if not self._fs.exists(self._path(self.path)):
            return []
        names = [s.getPath().getName() for s in self._fs.listStatus(self._path(self.path))]
        found = [(*map(int, m.groups()), n) for n in names if (m := pattern.fullmatch(n))]
        return sorted(v for v in found if self._fs.exists(self._path(f"{self.path}/{v[-1]}/_SUCCESS")))

    def _drop(self, name: str) -> None:
        self._fs.delete(self._path(f"{self.path}/{name}"), True)


class StateStore(_Folder):
    """Versions of the whole state below one folder."""

    def _versions(self) -> list[tuple[int, int, str]]:
        """(place in the order of commits, segment, folder)."""
        return self._complete(_VERSION)

    def has(self, segment: int) -> bool:
        """Whether this segment's scores are in the state."""
        return segment in self.segments()

    def segments(self) -> list[int]:
        """Committed segments, in the order of their commits."""
        return [v[1] for v in self._versions()]

    def read(self) -> DataFrame:
        """The version committed last; an empty state before any. Segments may come in any order."""
        done = self._versions()
        if not done:
            return self.spark.createDataFrame([], STATE_SCHEMA)
        return self.spark.read.schema(STATE_SCHEMA).parquet(f"{self.path}/{done[-1][2]}")

    def commit(self, segment: int, state: DataFrame) -> None:
        """Writes the state after this segment. Never touches an older version; what a broken run left of this one is replaced."""
        done = self._versions()
        if segment in [v[1] for v in done]:
            return
        place = done[-1][0] + 1 if done else 0
        state.select("u", "v", "score", "n_segments", "last_segment").write.mode("overwrite").parquet(f"{self.path}/version-{place:08d}-of-{segment}")


class SegmentStore(_Folder):
    """The bins and scores of every segment, below one folder.

    A commit writes the scores of one segment only. The state is the sum of every segment's last scores: what a
    snapshot holds and, of segments scored since, the new scores less those that the snapshot has. Scores are
    revised by another commit under the number of the batch that brought new bins, so late data takes back exactly
    what its segment had added, and a batch that comes again changes nothing.
    """

    def _revisions(self) -> dict[int, list[tuple[int, int, str]]]:
        """Of each segment: (place in the order of commits, batch, folder), in order."""
        out: dict[int, list[tuple[int, int, str]]] = {}
        for place, segment, batch, name in self._complete(_SCORES):
            out.setdefault(segment, []).append((place, batch, name))
        return out

    def segments(self) -> list[int]:
        """Segments with scores."""
        return sorted(self._revisions())

    def has(self, segment: int, batch: int | None = None) -> bool:
        """Whether the segment has scores or, with ``batch``, scores of that batch or a later one."""
        done = self._revisions().get(segment, [])
        return bool(done) if batch is None else any(b >= batch for _, b, _ in done)

    def commit(self, segment: int, scored: DataFrame, batch: int = 0) -> None:
        """Writes a segment's scores (u, v, score). What a broken run left is replaced."""
        if self.has(segment, batch):
            return
        place = 1 + max((r[-1][0] for r in self._revisions().values()), default=max((p for p, _ in self._complete(_SNAPSHOT)), default=-1))
        scored.select("u", "v", "score").write.mode("overwrite").parquet(f"{self.path}/scores-{place:08d}-of-{segment}-at-{batch}")

    def scores(self, segment: int) -> DataFrame:
        """The segment's last scores."""
        done = self._revisions().get(segment)
        rows = self.spark.read.schema("u long, v long, score double").parquet(f"{self.path}/{done[-1][2]}") if done else self.spark.createDataFrame([], "u long, v long, score double")
        return rows.withColumn("segment", F.lit(segment).cast("long"))

    def _signed(self, names: list[tuple[int, str]], sign: int) -> DataFrame:
        """State rows of these (segment, folder): one read over all folders, the segment from the folder's name."""
        rows = self.spark.read.schema("u long, v long, score double").parquet(*[f"{self.path}/{n}" for _, n in names])
        segment = F.regexp_extract(F.input_file_name(), r"scores-\d+-of-(-?\d+)-at-", 1).cast("long")
        return rows.select("u", "v", (F.col("score") * sign).alias("score"), F.lit(sign).cast("long").alias("n_segments"), (segment if sign > 0 else F.lit(None).cast("long")).alias("last_segment"))

    def read(self) -> DataFrame:
        """The state: u, v, score, n_segments, last_segment."""
        snapshots = self._complete(_SNAPSHOT)
        upto = snapshots[-1][0] if snapshots else -1
        more, less = [], []
        for segment, done in self._revisions().items():
            if done[-1][0] > upto:
                more.append((segment, done[-1][2]))
                less += [(segment, n) for place, _, n in done if place <= upto][-1:]
        rows = self.spark.read.schema(STATE_SCHEMA).parquet(f"{self.path}/{snapshots[-1][1]}") if snapshots else self.spark.createDataFrame([], STATE_SCHEMA)
        for names, sign in ((more, 1), (less, -1)):
            if names:
                rows = rows.unionByName(self._signed(names, sign))
        out = rows.groupBy("u", "v").agg(F.sum("score").alias("score"), F.sum("n_segments").alias("n_segments"), F.max("last_segment").alias("last_segment"))
        return out.where("n_segments > 0")

    def compact(self, keep: int = 2) -> None:
        """Writes a snapshot, drops all but the last ``keep`` of them, and scores that were revised before the oldest one kept."""
        last = max((r[-1][0] for r in self._revisions().values()), default=-1)
        if last > max((p for p, _ in self._complete(_SNAPSHOT)), default=-1):
            self.read().write.mode("overwrite").parquet(f"{self.path}/snapshot-{last:08d}")
        snapshots = self._complete(_SNAPSHOT)
        for _, name in snapshots[:-keep]:
            self._drop(name)
        oldest = snapshots[-keep:][0][0] if snapshots else -1
        for done in self._revisions().values():
            for _, _, name in [r for r in done if r[0] <= oldest][:-1]:
                self._drop(name)

    def add_bins(self, batch: int, binned: DataFrame) -> list[int]:
        """Writes a batch's bins (channel, entity, bin, cnt, segment), again if it comes again; returns its segments."""
        path = f"{self.path}/bins/batch={batch}"
        binned.select("channel", "entity", "bin", "cnt", "segment").repartition("segment").write.mode("overwrite").partitionBy("segment").parquet(path)
        names = [s.getPath().getName() for s in self._fs.listStatus(self._path(path))]
        return sorted(int(n.partition("=")[2]) for n in names if n.startswith("segment="))

    def bins(self, segments: list[int]) -> DataFrame:
        """All batches' bins of these segments, added up. Only their folders are read."""
        rows = self.spark.read.schema(BINS_SCHEMA).parquet(f"{self.path}/bins").where(F.col("segment").isin(segments))
        return rows.groupBy("segment", "channel", "entity", "bin").agg(F.sum("cnt").alias("cnt"))

    def note_late(self, batch: int, segments: list[int]) -> None:
        """Writes how many events a batch brought for segments that had scores already."""
        rows = self.spark.read.schema(BINS_SCHEMA).parquet(f"{self.path}/bins").where((F.col("batch") == batch) & F.col("segment").isin(segments))
        rows.groupBy("batch", "segment").agg(F.sum("cnt").alias("n_late")).write.mode("overwrite").parquet(f"{self.path}/late/of-{batch}")

    def late(self) -> DataFrame:
        """batch, segment, n_late: events that came after their segment was first scored. They count in its last scores."""
        schema = "batch long, segment long, n_late long"
        if not self._fs.exists(self._path(f"{self.path}/late")):
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(f"{self.path}/late")
