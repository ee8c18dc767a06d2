"""Cosine similarities by a grid of blocks: what a query keeps of the pairs is chosen where they are computed.

Where nearly every two entities share a bin, the pairs of an inverted index are nearly all pairs there are, and they
are shuffled before any is dropped. Here vectors move instead: a task gets a block of either side, multiplies them
a slice at a time and returns only the pairs that may be wanted (from a least similarity on, or the best of the
block for either side). Products are exact: counts are whole numbers, in 4-byte floats where no dot product can
reach 2**24 and in doubles otherwise. The pairs and their similarities are those of ``similarity.pairwise_cosine``.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from channelalign.sources.shared import written

#: Entities of a block, cells of a slice of products, and cells of a dense side at a time: a task's memory.
BLOCK = 8192
SLICE = 1 << 22
DENSE = 1 << 23
#: Cells of a dense product, each of a pair and a bin, that cost no more than one product of two counts found by an index.
DENSE_WORTH = 400
#: Rounded similarities are off by less than this share; what is nearer to a bound is decided by doubles.
NEAR = 1e-6
#: Cells of a slice that are looked through at a time: the pairs of an Arrow batch at most, or those of one entity.
BATCH = 1 << 18


def _packed(side: DataFrame, group: list[str], entity: str, cnt: str, sq: str, left: bool) -> DataFrame:
    cells = side.groupBy(*group, F.col(entity).alias("id")).agg(F.max(sq).alias("sq"), F.collect_list(F.struct("bin", F.col(cnt).alias("cnt"))).alias("x"))
    return cells.select(*group, F.lit(left).alias("is_left"), "id", "sq", F.col("x.bin").alias("bins"), F.col("x.cnt").alias("cnts"))


def pack(a: DataFrame, b: DataFrame, group: list[str]) -> DataFrame:
    """group, is_left, id, sq, bins, cnts of both sides. a: group, u, bin, cu, squ; b: group, v, bin, cv, sqv."""
    return _packed(a, group, "u", "cu", "squ", True).unionByName(_packed(b, group, "v", "cv", "sqv", False))


#: Partitions for each pair of blocks, so that few share one; each has so many vectors at least, and there are so many at most.
PARTS, PART_ROWS, MOST_PARTS = 4, 512, 4096


def _dealt(packed: DataFrame, group: list[str], least: tuple[int, int]) -> DataFrame:
    """group, i, j and the vectors, each once for every block of the other side. Few bytes are much work here, so partitions are numbered by pairs of blocks."""
    packed = written(packed, "vectors")
    both = [F.greatest(F.ceil(F.count_if(F.col("is_left") == side) / BLOCK), F.lit(n)).cast("int").alias(name) for side, n, name in ((True, least[0], "_is"), (False, least[1], "_js"))]
    sizes = packed.groupBy(*group).agg(*both, F.count_if("is_left").alias("_us"), F.count_if(~F.col("is_left")).alias("_vs"))
    cells, dealt = sizes.agg(F.sum(F.col("_is") * F.col("_js")), F.sum(F.col("_us") * F.col("_js") + F.col("_vs") * F.col("_is"))).first()
    parts = max(1, min(PARTS * (cells or 0), -(-(dealt or 0) // PART_ROWS), MOST_PARTS))
    sizes = sizes.drop("_us", "_vs")
    low, high, most = packed.agg(F.min(F.array_min("bins")), F.max(F.array_max("bins")), F.max(F.array_max("cnts"))).first()
    narrow = "array<int>" if max(abs(low or 0), abs(high or 0), most or 0) < 1 << 31 else "array<long>"  # half the bytes, where no number is cut
    rows = packed.join(sizes, group) if group else packed.crossJoin(F.broadcast(sizes))
    own = F.pmod(F.xxhash64("id"), F.when(F.col("is_left"), F.col("_is")).otherwise(F.col("_js"))).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.when(F.col("is_left"), F.col("_js")).otherwise(F.col("_is")) - 1))
    rows = rows.withColumn("_own", own).withColumn("_other", other)
    i, j = (F.when(F.col("is_left") == side, F.col("_own")).otherwise(F.col("_other")) for side in (True, False))
    rows = rows.select(*group, i.alias("i"), j.alias("j"), "is_left", "id", "sq", F.col("bins").cast(narrow).alias("bins"), F.col("cnts").cast(narrow).alias("cnts"))
    return rows.repartition(parts, *group, "i", "j")


class _Side:
    """The vectors of a block: ids, squared norms and their cells."""

    def __init__(self, parts: list[pa.RecordBatch]):
        self.ids = np.concatenate([p.column("id").to_numpy() for p in parts])
        self.sq = np.concatenate([p.column("sq").to_numpy() for p in parts])
        self.ends = np.cumsum(np.concatenate([p.column("bins").value_lengths().to_numpy() for p in parts]))
        self.bins = np.concatenate([p.column("bins").flatten().to_numpy() for p in parts])
        self.cnts = np.concatenate([p.column("cnts").flatten().to_numpy() for p in parts])

    def keep(self, bins: np.ndarray) -> None:
        """Only the cells of these bins, numbered by their place among them."""
        place = np.minimum(np.searchsorted(bins, self.bins), max(len(bins) - 1, 0))
        good = bins[place] == self.bins if len(bins) else np.zeros(len(self.bins), bool)
        owner = np.repeat(np.arange(len(self.ids)), np.diff(self.ends, prepend=0))
        self.owner, self.place, self.cnts = owner[good], place[good], self.cnts[good]
        self.starts = np.searchsorted(self.owner, np.arange(len(self.ids) + 1))

    def dense(self, first: int, last: int, low: int, high: int, kind: type) -> np.ndarray:
        """The counts of some entities in some bins."""
        cells = slice(self.starts[first], self.starts[last])
        owner, place, cnts = self.owner[cells] - first, self.place[cells] - low, self.cnts[cells]
        out = np.zeros((last - first, high - low), kind)
        inside = (place >= 0) & (place < high - low)
        out[owner[inside], place[inside]] = cnts[inside]
        return out


def _indexed(x: _Side, y: _Side, met: np.ndarray, kind: type) -> Iterator[tuple[int, np.ndarray]]:
    """What ``_slices`` gives, by an index of the right cells by bin: work for common bins only. met: how many right cells a bin has."""
    order = np.argsort(y.place, kind="stable")
    owner, cnts, begin = y.owner[order], y.cnts[order], np.cumsum(met) - met
    n, step = len(y.ids), max(1, SLICE // len(y.ids))
    few = max(1, BATCH // n)  # rows whose products are made at a time
    for first in range(0, len(x.ids), step):
        dots = np.empty((min(step, len(x.ids) - first), n), kind)
        for some in range(0, len(dots), few):
            part = dots[some : some + few]
            cells = slice(x.starts[first + some], x.starts[first + some + len(part)])
            place = x.place[cells]
            many = met[place]
            at = np.arange(many.sum()) + np.repeat(begin[place] - (np.cumsum(many) - many), many)
            pairs = np.repeat((x.owner[cells] - first - some) * n, many) + owner[at]
            part[:] = np.bincount(pairs, np.repeat(x.cnts[cells], many) * cnts[at], len(part) * n).reshape(part.shape)
        yield first, dots


def _slices(x: _Side, y: _Side) -> Iterator[tuple[int, np.ndarray]]:
    """(first row, dot products of some left entities with all right ones)."""
    bins = np.intersect1d(x.bins, y.bins)
    x.keep(bins), y.keep(bins)
    kind = np.float32 if float(x.sq.max()) * float(y.sq.max()) < 2.0**48 else np.float64
    met = np.bincount(y.place, minlength=len(bins))
    if len(bins) and float(met[x.place].sum()) * DENSE_WORTH < float(len(x.ids)) * len(y.ids) * len(bins):
        yield from _indexed(x, y, met, kind)
        return
    width = max(1, DENSE // max(len(y.ids), 1))
    chunks = [(low, min(low + width, len(bins))) for low in range(0, len(bins), width)]
    held = y.dense(0, len(y.ids), *chunks[0], kind) if len(chunks) == 1 else None
    step = max(1, SLICE // len(y.ids))
    for first in range(0, len(x.ids) if chunks else 0, step):
        last = min(first + step, len(x.ids))
        dots = None
        for low, high in chunks:
            part = x.dense(first, last, low, high, kind) @ (y.dense(0, len(y.ids), low, high, kind) if held is None else held).T
            dots = part if dots is None else np.add(dots, part, out=dots)
        yield first, dots


def _mth(values: np.ndarray, m: int) -> np.ndarray:
    """The m-th largest number of each row, 0 where there are fewer."""
    if values.shape[1] < m:
        return np.zeros(len(values), values.dtype)
    return values.max(axis=1) if m == 1 else np.partition(values, values.shape[1] - m, axis=1)[:, -m]


def _first(by: np.ndarray, sim: np.ndarray, other: np.ndarray, m: int, ties: bool) -> np.ndarray:
    """Which pairs are among the m first of their ``by`` (other breaks ties), or as good as its best (ties)."""
    order = np.lexsort((other, -sim, by))
    start = np.r_[True, by[order][1:] != by[order][:-1]] if len(order) else np.zeros(0, bool)
    begin = np.maximum.accumulate(np.where(start, np.arange(len(order)), 0))
    good = sim[order] == sim[order][begin] if ties else np.arange(len(order)) - begin < m
    out = np.zeros(len(order), bool)
    out[order[good]] = True
    return out


class _Columns:
    """Candidates for the m best of each right entity, over all slices."""

    def __init__(self, n: int, m: int):
        self.m, self.mth = m, np.zeros(n)
        self.p, self.q, self.dot, self.near = (np.zeros(0, t) for t in (np.int64, np.int64, np.float64, np.float64))

    def add(self, first: int, dots: np.ndarray, near: np.ndarray, least: float) -> None:
        if len(self.p) == 0 and self.m > 1:
            self.mth = np.maximum(self.mth, _mth(np.ascontiguousarray(near.T), self.m))
        elif self.m == 1:
            self.mth = np.maximum(self.mth, near.max(axis=0))
        floor = np.maximum(self.mth * (1 - NEAR), least).astype(near.dtype)
        at = np.flatnonzero(near >= floor[None])
        p, q = np.divmod(at, near.shape[1])
        self.p, self.q = np.concatenate([self.p, p + first]), np.concatenate([self.q, q])
        self.dot, self.near = np.concatenate([self.dot, dots.ravel()[at]]), np.concatenate([self.near, near.ravel()[at]])
        if self.m > 1:
            order = np.lexsort((-self.near, self.q))
            starts = np.searchsorted(self.q[order], np.arange(len(self.mth)))
            many = np.bincount(self.q, minlength=len(self.mth)) >= self.m
            self.mth[many] = np.maximum(self.mth[many], self.near[order][starts[many] + self.m - 1])
        good = self.near >= self.mth[self.q] * (1 - 2 * NEAR)
        self.p, self.q, self.dot, self.near = self.p[good], self.q[good], self.dot[good], self.near[good]


def cosine(dot: np.ndarray, sqx: np.ndarray, sqy: np.ndarray) -> np.ndarray:
    return dot / np.sqrt((sqx * sqy).astype(float))


def jaccard(dot: np.ndarray, sqx: np.ndarray, sqy: np.ndarray) -> np.ndarray:
    """Of sets, whose counts are 1: never over the cosine, so a bound on that one loses none of it."""
    return dot / (sqx + sqy - dot)


def _every(x: _Side, y: _Side, theta: float | None, measure: Callable[..., np.ndarray] = cosine) -> Iterator[tuple[np.ndarray, ...]]:
    """(u, their numbers of pairs, v, dot, sim) of all pairs of two blocks of at least theta (None: that share a bin), some left entities at a time."""
    step = max(1, BATCH // max(len(y.ids), 1))
    for first, dots in _slices(x, y):
        for some in range(0, len(dots), step):
            part = dots[some : some + step]
            kept = part > 0
            counts = kept.sum(axis=1)
            p, q = np.repeat(np.arange(first + some, first + some + len(part)), counts), np.flatnonzero(kept)
            q -= (p - first - some) * len(y.ids)
            dot = np.rint(part[kept]).astype(np.int64)
            sim = measure(dot, x.sq[p], y.sq[q])
            if theta is not None:
                good = sim >= theta
                counts = np.bincount(p[good] - first - some, minlength=len(part))
                q, dot, sim = q[good], dot[good], sim[good]
            at = np.flatnonzero(counts)
            if len(at):
                yield x.ids[first + some + at], counts[at], y.ids[q], dot, sim


def _wanted(x: _Side, y: _Side, m: int, ties: bool, ways: str, theta: float | None, measure: Callable[..., np.ndarray] = cosine) -> Iterator[tuple[np.ndarray, ...]]:
    """(u, v, dot, sim, best of u, best of v) of pairs of two blocks. ways: u, v, uv, or nothing for all pairs of at least theta."""
    if not ways:
        for u, counts, v, dot, sim in _every(x, y, theta, measure):
            yield np.repeat(u, counts), v, dot, sim, np.zeros(len(v), bool), np.zeros(len(v), bool)
        return
    ru, rv = 1 / np.sqrt(x.sq.astype(float)), 1 / np.sqrt(y.sq.astype(float))
    least = max((theta or 0.0) * (1 - NEAR), 1e-30)
    rows: list[tuple[np.ndarray, ...]] = []
    columns = _Columns(len(y.ids), m)

    def exact(p: np.ndarray, q: np.ndarray, dot: np.ndarray) -> tuple[np.ndarray, ...]:
        dot = np.rint(dot).astype(np.int64)
        sim = measure(dot, x.sq[p], y.sq[q])
        good = (dot > 0) & (sim >= (0.0 if theta is None else theta))
        return p[good], q[good], dot[good], sim[good]

    for first, dots in _slices(x, y):
        near = dots * rv.astype(dots.dtype)[None]
        near *= ru[first : first + len(dots)].astype(dots.dtype)[:, None]
        if "v" in ways:
            columns.add(first, dots, near, least)
        if ways != "v":
            floor = np.maximum(_mth(near, m) * (1 - NEAR), least)
            at = np.flatnonzero(near >= floor.astype(near.dtype)[:, None])
            p, q = np.divmod(at, near.shape[1])
            rows.append(exact(p + first, q, dots.ravel()[at]))
    p, q, dot, sim = (np.concatenate([r[k] for r in rows]) if rows else np.zeros(0, t) for k, t in enumerate((np.int64, np.int64, np.int64, float)))
    f = _first(p, sim, y.ids[q], m, ties)
    p, q, dot, sim = p[f], q[f], dot[f], sim[f]
    cp, cq, cdot, csim = exact(columns.p, columns.q, columns.dot)
    b = _first(cq, csim, x.ids[cp], m, ties)
    cp, cq, cdot, csim = cp[b], cq[b], cdot[b], csim[b]
    of_rows, of_columns = p * len(y.ids) + q, cp * len(y.ids) + cq
    more = ~np.isin(of_columns, of_rows)
    yield (
        np.concatenate([x.ids[p], x.ids[cp[more]]]), np.concatenate([y.ids[q], y.ids[cq[more]]]), np.concatenate([dot, cdot[more]]), np.concatenate([sim, csim[more]]),
        np.r_[np.ones(len(p), bool), np.zeros(int(more.sum()), bool)], np.r_[np.isin(of_rows, of_columns), np.ones(int(more.sum()), bool)],
    )


def grid(packed: DataFrame, group: list[str], m: int = 1, ties: bool = True, ways: str = "", theta: float | None = None, least: tuple[int, int] = (1, 1), measure: Callable[..., np.ndarray] = cosine) -> DataFrame:
    """group, u, v, dot, sim, near_u, near_v: pairs of equal group from what ``pack`` gives. least: at least so many blocks of either side; measure: sim of a pair, the cosine unless ways is "".

    ways "" gives all pairs of at least theta (None: all that share a bin); "u", "v" or "uv" those that within
    their two blocks are among the m best of the side (near_u, near_v), with all that equal the best if ties.
    """
    if ways and measure is not cosine:
        raise ValueError("the best of a block are ranked by cosine")
    dealt = _dealt(packed, group, least)
    made = [f"`{f.name}` {f.dataType.simpleString()}" for f in dealt.select(*group).schema.fields]
    best = {"u": "long", "v": "long", "dot": "long", "sim": "double", "near_u": "boolean", "near_v": "boolean"}
    packed_pairs = {"u": "long", "vs": "array<long>", "dots": "array<long>", "sims": "array<double>"}  # a row of Python's for each entity and block, not for each pair
    columns = best if ways else packed_pairs
    schema, names = ", ".join([*made, *[f"{n} {t}" for n, t in columns.items()]]), [*group, *columns]

    def multiply(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: dict[bool, list[pa.RecordBatch]] = {True: [], False: []}
        for batch in batches:
            for left in parts:
                own = batch.filter(batch.column("is_left") if left else pc.invert(batch.column("is_left")))
                if own.num_rows:
                    parts[left].append(own)
        if not (parts[True] and parts[False]):
            return
        x, y = _Side(parts[True]), _Side(parts[False])
        if ways:
            found = ([pa.array(c) for c in f] for f in _wanted(x, y, m, ties, ways, theta, measure))
        else:
            found = ([pa.array(u), *[pa.ListArray.from_arrays(np.r_[0, np.cumsum(n)].astype(np.int32), pa.array(c)) for c in rest]] for u, n, *rest in _every(x, y, theta, measure))
        for f in found:
            yield pa.RecordBatch.from_arrays([*[pa.repeat(k, len(f[0])) for k in key[: len(group)]], *f], names=names)

    pairs = dealt.groupBy(*group, "i", "j").applyInArrow(multiply, schema)
    if ways:
        return pairs
    pairs = pairs.select(*group, "u", F.posexplode("vs").alias("_k", "v"), "dots", "sims")
    return pairs.select(*group, "u", "v", F.get("dots", "_k").alias("dot"), F.get("sims", "_k").alias("sim"), F.lit(False).alias("near_u"), F.lit(False).alias("near_v"))


def matched(packed: DataFrame, group: list[str], how: str = "intersect", rule: str = "best", theta: float | None = None, m: int = 1, keys: tuple[str, ...] = (), several: bool = False) -> DataFrame:
    """keys, u, v, dot, sim: what ``matching.reconcile`` finds among all pairs, ranked among the best of each block. keys: those columns of the group within which pairs are ranked; several: a pair may be in several groups."""
    def once(found: DataFrame) -> DataFrame:
        if not several:
            return found
        return found.groupBy(*keys, "u", "v").agg(*[F.max(c).alias(c) for c in ("dot", "sim", "near_u", "near_v")])

    if rule == "threshold":
        return once(grid(packed, group, theta=theta)).select(*keys, "u", "v", "dot", "sim")
    if rule not in ("best", "top"):
        raise ValueError(f"no rule {rule}")
    if how not in ("intersect", "union", "forward", "backward"):
        raise ValueError(f"no way {how}")
    m = 1 if rule == "best" else m
    near = once(grid(packed, group, m, rule == "best", {"forward": "u", "backward": "v"}.get(how, "uv"), theta))

    def place(by: str, other: str, flag: str):
        # Pairs that a block kept for the other side only are not ranked on this one.
        over = Window.partitionBy(*keys, by, flag)
        order = F.rank().over(over.orderBy(F.col("sim").desc())) if rule == "best" else F.row_number().over(over.orderBy(F.col("sim").desc(), other))
        return F.col(flag) & (order <= m)

    if how in ("forward", "backward"):
        found = near.where(F.col("near_u" if how == "forward" else "near_v")).withColumn("_k", place(*(("u", "v", "near_u") if how == "forward" else ("v", "u", "near_v")))).where("_k")
    else:
        found = near.withColumn("_f", place("u", "v", "near_u")).withColumn("_b", place("v", "u", "near_v")).where("_f AND _b" if how == "intersect" else "_f OR _b")
    return found.select(*keys, "u", "v", "dot", "sim")
