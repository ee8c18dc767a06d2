"""Spectral embedding of time-warped series: affinity, Laplacian, eigenvectors. For a bounded number of series.

The number of distances grows with the square of the number of series. Up to MOST_SERIES the map is exact; beyond
it landmarks are mapped exactly and all others placed among them in one pass (approximate, asked for by name).
Affinities come to the driver as rows of a matrix of 4-byte numbers: 100 MB for MOST_SERIES.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import islice

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from channelalign.functions import dtw
from channelalign.operators.binning import rebin, to_vectors

MOST_SERIES = 5000


def coarsen(binned: DataFrame, n_bins: int, most_bins: int) -> tuple[DataFrame, int]:
    """(binned with at most so many bins, their number): warping costs grow with the square of it."""
    factor = max(1, -(-n_bins // most_bins))
    return (rebin(binned, factor) if factor > 1 else binned), -(-n_bins // factor)


def series(binned: DataFrame, n_bins: int) -> DataFrame:
    """vectors with a place ``i`` (0, 1, ... by hash bucket, channel and entity) and n_bins. Numbered by counts of 256 buckets, so no task sees all series."""
    v = to_vectors(binned)
    bucket = F.pmod(F.xxhash64("channel", "entity"), F.lit(256))
    counts = binned.select("channel", "entity").distinct().groupBy(bucket.alias("_b")).agg(F.count(F.lit(1)).alias("_n"))
    before = counts.select("_b", (F.sum("_n").over(Window.orderBy("_b")) - F.col("_n")).alias("_before"))  # over 256 rows
    own = v.withColumn("_b", bucket).withColumn("_r", F.row_number().over(Window.partitionBy("_b").orderBy("channel", "entity")) - 1)
    return own.join(F.broadcast(before), "_b").withColumn("i", (F.col("_before") + F.col("_r")).cast("long")).drop("_b", "_r", "_before").withColumn("n_bins", F.lit(n_bins))


def _apart(x: tuple[np.ndarray, np.ndarray], y: tuple[np.ndarray, np.ndarray], n_bins: int, band: int | None) -> float:
    if band is None and (len(x[0]) + len(y[0])) * 4 < 2 * n_bins:
        return dtw.run_distance(x, y)
    return dtw.distance(np.repeat(*x), np.repeat(*y), band)


#: Series of more bins are warped pair by pair, by their runs.
DENSE_BINS = 512


def _all_apart(xs: list[tuple[np.ndarray, np.ndarray]], ys: list[tuple[np.ndarray, np.ndarray]], n_bins: int, band: int | None) -> np.ndarray:
    """Distances of every x from every y, both as runs."""
    if band is None and n_bins <= DENSE_BINS and xs and ys:
        return dtw.all_distances(np.stack([np.repeat(*x) for x in xs]), np.stack([np.repeat(*y) for y in ys]))
    return np.array([_apart(x, y, n_bins, band) for x in xs for y in ys]).reshape(len(xs), len(ys))


#: Series of a block, and distances of a task's slice.
BLOCK = 8192
SLICE = 1 << 20
#: Partitions for each two blocks, so that few share one.
PARTS = 4
#: Left and right places of a packed row of pairs: Spark holds all pairs that it makes of one row. Rows of an Arrow batch.
OWN, OTHERS, ROWS = 16, 512, 256


def _blocks_meet(vectors: DataFrame, blocks: int) -> DataFrame:
    """p, q, b, n_bins, bins, cnts, places: blocks of series meet each other once, in groups (p, q); a task holds two blocks. There are more than ``blocks`` of them where one would be too large for a task.

    Equal series of a block are one row with all their places, so it is forms that are sent to every block, not series.
    """
    blocks = max(blocks, -(-vectors.count() // BLOCK))
    v = vectors.groupBy(F.pmod("i", F.lit(blocks)).cast("int").alias("b"), "n_bins", "bins", "cnts").agg(F.collect_list("i").alias("places"))
    grid = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    met = v.withColumn("o", grid).withColumns({"p": F.least("b", "o"), "q": F.greatest("b", "o")}).drop("o")
    return met.repartition(PARTS * blocks * (blocks + 1) // 2, "p", "q")


def _form_distances(xs: list[tuple], ys: list[tuple], n_bins: int, band: int | None) -> np.ndarray:
    """Distances of forms (bins, counts). Without a band, zeros at the end of both cost nothing beyond the first, so series are no longer than the longer one of their class (by powers of two) needs."""
    if band is not None:
        return _all_apart([dtw.compress(*x, n_bins) for x in xs], [dtw.compress(*y, n_bins) for y in ys], n_bins, band)
    need = [np.array([1 << int(max(f[0], default=0) + 1).bit_length() for f in side]) for side in (xs, ys)]
    out = np.empty((len(xs), len(ys)))
    for i in np.unique(need[0]):
        for j in np.unique(need[1]):
            at, of = np.flatnonzero(need[0] == i), np.flatnonzero(need[1] == j)
            n = min(n_bins, int(max(i, j)))
            out[np.ix_(at, of)] = _all_apart([dtw.compress(*xs[k], n) for k in at], [dtw.compress(*ys[k], n) for k in of], n, None)
    return out


def _block_distances(group: pd.DataFrame, band: int | None) -> Iterator[tuple[list[np.ndarray], np.ndarray, np.ndarray]]:
    """(places of each of some left forms, places of the right series, distances of the former from the latter) of a task's two blocks, at most SLICE distances at a time or those of one form."""
    p, q, n_bins = int(group["p"].iloc[0]), int(group["q"].iloc[0]), int(group["n_bins"].iloc[0])
    left, right = group[group["b"] == p], group[group["b"] == q]
    if not (len(left) and len(right)):
        return
    lefts, rights = ([(np.asarray(x), np.asarray(y)) for x, y in zip(side["bins"], side["cnts"], strict=True)] for side in (left, right))
    at, form = np.concatenate(list(right["places"])), np.repeat(np.arange(len(right)), [len(x) for x in right["places"]])
    step = max(1, SLICE // len(at))
    for first in range(0, len(left), step):
        d = _form_distances(lefts[first : first + step], rights, n_bins, band)
        yield list(left["places"].iloc[first : first + step]), at, d[:, form]


def _pairs(vectors: DataFrame, of: Callable[[np.ndarray], np.ndarray], name: str, band: int | None, blocks: int) -> DataFrame:
    """(i, j, name), i < j: what ``of`` makes of the warping distance of every two series. A task returns rows of equal left series against some right ones, and rows of pairs are made of them outside of Python."""

    def packed_rows(group: pd.DataFrame) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        for own, others, d in _block_distances(group, band):
            for places, made in zip(own, of(d), strict=True):
                for x in range(0, len(places), OWN):
                    for y in range(0, len(others), OTHERS):
                        yield places[x : x + OWN], others[y : y + OTHERS], made[y : y + OTHERS]

    def meet(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group = pa.Table.from_batches(list(batches)).to_pandas()
        rows = packed_rows(group)
        while some := list(islice(rows, ROWS)):
            lists = (pa.ListArray.from_arrays(np.cumsum([0, *map(len, x)]).astype(np.int32), pa.array(np.concatenate(x))) for x in zip(*some, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array([key[0] == key[1]] * len(some)), *lists], names=["same", "own", "others", "ds"])

    packed = _blocks_meet(vectors, blocks).groupBy("p", "q").applyInArrow(meet, "same boolean, own array<long>, others array<long>, ds array<double>")
    each = packed.select("same", F.explode("own").alias("_x"), "others", "ds").select("same", "_x", F.posexplode("others").alias("_k", "_y"), "ds")
    each = each.where(~F.col("same") | (F.col("_x") < F.col("_y")))  # within a block, every two series meet twice
    return each.select(F.least("_x", "_y").alias("i"), F.greatest("_x", "_y").alias("j"), F.get("ds", "_k").alias(name))


def distances(vectors: DataFrame, band: int | None = None, blocks: int = 8) -> DataFrame:
    """(i, j, d), i < j: the warping distance of every two series. The rows grow with the square of the series; a task holds a slice of them."""
    return _pairs(vectors, lambda d: d, "d", band, blocks)


def affinity(vectors: DataFrame, tau: float, band: int | None = None, blocks: int = 8) -> DataFrame:
    """(i, j, w), i < j: exp(-distance / tau)."""
    if tau <= 0:
        raise ValueError("tau must be above 0")
    return _pairs(vectors, lambda d: np.exp(-d / tau), "w", band, blocks)


def affinity_rows(vectors: DataFrame, tau: float, band: int | None = None, blocks: int = 8) -> DataFrame:
    """(i, js, ws): of each series and block of others, their places and affinities, as little-endian bytes of 8 and 4 bytes a number."""

    def meet(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group = pa.Table.from_batches(list(batches)).to_pandas()
        for own, others, d in _block_distances(group, band):
            js, ws = others.astype("<i8").tobytes(), np.exp(-d / tau).astype("<f4")
            for places, w in zip(own, ws, strict=True):
                for some in range(0, len(places), 64):
                    part = places[some : some + 64]
                    yield pa.RecordBatch.from_arrays([pa.array(part), pa.array([js] * len(part)), pa.array([w.tobytes()] * len(part))], names=["i", "js", "ws"])

    return _blocks_meet(vectors, blocks).groupBy("p", "q").applyInArrow(meet, "i long, js binary, ws binary")


def laplacian(w: DataFrame) -> DataFrame:
    """(i, j, l) of degree minus affinity, with the diagonal, from edges i < j."""
    to, back = (F.when(F.col("_way"), a).otherwise(F.col(b)) for a, b in ((F.col("i"), "j"), (F.col("j"), "i")))
    both = w.select("i", "j", "w", F.explode(F.array(F.lit(True), F.lit(False))).alias("_way")).select(to.alias("i"), back.alias("j"), "w")  # edges are computed once for both ways
    degrees = both.groupBy("i").agg(F.sum("w").alias("l")).select("i", F.col("i").alias("j"), "l")
    return both.select("i", "j", (-F.col("w")).alias("l")).unionByName(degrees)


def _eigen(w: np.ndarray, p: int, zero: float) -> tuple[np.ndarray, np.ndarray]:
    values, vectors = np.linalg.eigh(np.diag(w.sum(axis=1)) - w)
    first = int((values <= zero * max(1.0, values[-1])).sum())
    chosen = vectors[:, first : first + p]
    peak = chosen[np.abs(chosen).argmax(axis=0), np.arange(chosen.shape[1])] if chosen.size else np.ones(chosen.shape[1])
    return chosen * np.where(peak < 0, -1.0, 1.0), values[first : first + p]


def eigenmap(vectors: DataFrame, p: int, tau: float, band: int | None = None, zero_tol: float = 1e-9, landmarks: int | None = None, seed: int = 0, exact_to: int = 0) -> DataFrame:
    """(channel, entity, f): the entries of the first p eigenvectors of an eigenvalue above zero, ascending; the largest entry of each is positive.

    A graph in several parts has as many zero eigenvalues; all are skipped. landmarks: that many series, in hash
    order, are mapped exactly; another one lies at the affinity-weighted mean of the landmarks, approximately. exact_to: landmarks serve only for more series than that.
    """
    n = vectors.count()
    spark = vectors.sparkSession
    if n <= exact_to:
        landmarks = None
    if landmarks is None or landmarks >= n:
        if n > MOST_SERIES:
            raise ValueError(f"{n} series are over {MOST_SERIES}: choose a number of landmarks")
        chosen, names = vectors, [(r["i"], r["channel"], r["entity"]) for r in vectors.select("i", "channel", "entity").orderBy("i").collect()]
    else:
        if landmarks > MOST_SERIES:
            raise ValueError(f"at most {MOST_SERIES} landmarks")
        chosen = vectors.orderBy(F.xxhash64("channel", "entity", F.lit(seed)), "channel", "entity").limit(landmarks)  # a top-k: each task keeps its own least
        names = [(r["i"], r["channel"], r["entity"]) for r in chosen.select("i", "channel", "entity").orderBy("i").collect()]
        chosen = vectors.join(F.broadcast(spark.createDataFrame([(x[0],) for x in names], "i long")), "i", "left_semi")
    place = {x[0]: k for k, x in enumerate(names)}
    ids, w = np.array([x[0] for x in names], np.int64), np.zeros((len(names), len(names)))
    # At most MOST_SERIES squared numbers of 4 bytes, in packed rows, a partition of them at a time.
    for r in affinity_rows(chosen, tau, band).toLocalIterator():
        i, js = np.searchsorted(ids, r["i"]), np.searchsorted(ids, np.frombuffer(r["js"], "<i8"))
        w[i, js] = w[js, i] = np.frombuffer(r["ws"], "<f4")
    np.fill_diagonal(w, 0.0)
    at, _ = _eigen(w, p, zero_tol)
    exact = spark.createDataFrame([(c, e, [float(x) for x in at[k]]) for k, (_, c, e) in enumerate(names)], "channel string, entity long, f array<double>")
    if landmarks is None or landmarks >= n:
        return exact
    anchors = [(np.array(r["bins"]), np.array(r["cnts"])) for r in sorted(chosen.collect(), key=lambda r: place[r["i"]])]
    sent = spark.sparkContext.broadcast((anchors, at))

    def put(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known, where = sent.value
        for rows in batches:
            out = []
            for first in range(0, len(rows), 64):
                part = rows.iloc[first : first + 64]
                n_bins = int(part["n_bins"].iloc[0])
                mine = [dtw.compress(np.array(x), np.array(y), n_bins) for x, y in zip(part["bins"], part["cnts"], strict=True)]
                d = _all_apart(mine, [dtw.compress(b, c, n_bins) for b, c in known], n_bins, band)
                weight = np.exp(-(d - d.min(axis=1, keepdims=True)) / tau)  # shifted, so that far series do not vanish
                at_part = weight @ where / weight.sum(axis=1, keepdims=True)
                out += [(c, e, list(map(float, f))) for c, e, f in zip(part["channel"], part["entity"], at_part, strict=True)]
            yield pd.DataFrame(out, columns=["channel", "entity", "f"])

    rest = vectors.join(F.broadcast(exact.select("channel", "entity")), ["channel", "entity"], "left_anti").select("channel", "entity", "bins", "cnts", "n_bins")
    return exact.unionByName(rest.mapInPandas(put, "channel string, entity long, f array<double>"))
