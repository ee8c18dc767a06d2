"""Similarity of entities of two channels from their binned counts. Pairs: [keys,] u, v, dot, sim."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from channelalign.operators import blocks
from channelalign.sources.shared import written


def _sides(binned: DataFrame, left: str, right: str, labels: DataFrame | None, keys: tuple[str, ...]) -> tuple[DataFrame, DataFrame, list[str]]:
    """Rows of either channel with their vector's squared norm, and the columns that both must agree on. Labels with a column of the keys (the segment) hold for that key only."""
    rows = binned.where(F.col("channel").isin(left, right))
    norm = F.sum(F.col("cnt") * F.col("cnt")).over(Window.partitionBy(*keys, "channel", "entity"))
    rows = rows.withColumn("sq", norm)
    on = [*keys, "bin"]
    if labels is not None:
        by = [*[k for k in keys if k in labels.columns], "channel", "entity"]
        rows, on = rows.join(labels.select(*by, "cluster"), by), [*keys, "cluster", "bin"]
    a = rows.where(F.col("channel") == left).select(*on, F.col("entity").alias("u"), F.col("cnt").alias("cu"), F.col("sq").alias("squ"))
    b = rows.where(F.col("channel") == right).select(*on, F.col("entity").alias("v"), F.col("cnt").alias("cv"), F.col("sq").alias("sqv"))
    return a, b, on


def cosine(dot: str = "dot", squ: str = "squ", sqv: str = "sqv"):
    """dot over the root of both squared norms, all of which are exact integers."""
    return F.col(dot) / F.sqrt((F.col(squ) * F.col(sqv)).cast("double"))


def _salted(a: DataFrame, b: DataFrame, on: list[str], salts: int, hot: int) -> tuple[DataFrame, DataFrame, list[str]]:
    """Left rows of bins whose product of sides is over ``hot`` are dealt to ``salts`` parts, right rows are there once for each part."""
    sides = a.groupBy(*on).agg(F.count(F.lit(1)).alias("_a")).join(b.groupBy(*on).agg(F.count(F.lit(1)).alias("_b")), on)
    many = sides.where(F.col("_a") * F.col("_b") > hot).select(*on, F.lit(salts).alias("_parts"))
    a = a.join(many, on, "left").withColumn("_salt", F.pmod(F.xxhash64("u"), F.coalesce("_parts", F.lit(1)))).drop("_parts")
    b = b.join(many, on, "left").withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("_parts", F.lit(1)).cast("long") - 1))).drop("_parts")
    return a, b, [*on, "_salt"]


def pairwise_cosine(binned: DataFrame, left: str, right: str, labels: DataFrame | None = None, keys: tuple[str, ...] = (), min_sim: float | None = None, prune: bool = False, salts: int = 1, hot: int = 10_000_000, several: bool = False) -> DataFrame:
    """Cosine similarity of all pairs that share a bin, or of those of equal cluster (several: entities have several labels each).

    An inverted index in long form: rows meet on (keys, cluster, bin) and their products are summed per pair, with
    partial sums before the shuffle; norms travel with the rows, so pairs are shuffled once. keys: columns that
    pairs must share, such as the segment. With min_sim only pairs from there on are returned; prune finds them by
    an exact prefix filter. salts > 1 deals out bins with more than ``hot`` products.
    """
    a, b, on = _sides(binned, left, right, labels, keys)
    if prune:
        if min_sim is None:
            raise ValueError("pruning needs min_sim")
        if several:
            raise ValueError("pruning takes one label an entity")
        return _pruned(a, b, on, keys, min_sim)
    if salts > 1:
        a, b, on = _salted(a, b, on, salts, hot)
    met = a.join(b, on)
    if labels is not None:  # entities may have several labels: what a pair has in one cluster is all of its dot product
        met = met.groupBy(*keys, "cluster", "u", "v").agg(F.sum(F.col("cu") * F.col("cv")).alias("dot"), F.max("squ").alias("squ"), F.max("sqv").alias("sqv"))
        pairs = met.dropDuplicates([*keys, "u", "v"]) if several else met
        pairs = pairs.select(*keys, "u", "v", "dot", cosine().alias("sim"))
        return pairs if min_sim is None else pairs.where(F.col("sim") >= min_sim)
    pairs = met.groupBy(*keys, "u", "v").agg(F.sum(F.col("cu") * F.col("cv")).alias("dot"), F.max("squ").alias("squ"), F.max("sqv").alias("sqv"))
    pairs = pairs.select(*keys, "u", "v", "dot", cosine().alias("sim"))
    return pairs if min_sim is None else pairs.where(F.col("sim") >= min_sim)


def _products(a: DataFrame, b: DataFrame, on: list[str], over: int = 0) -> int:
    """Rows that a join of both sides makes, from counts alone; those of bins with more than ``over``."""
    sides = a.groupBy(*on).agg(F.count(F.lit(1)).alias("_a")).join(b.groupBy(*on).agg(F.count(F.lit(1)).alias("_b")), on)
    return sides.where(F.col("_a") * F.col("_b") > over).agg(F.sum(F.col("_a") * F.col("_b"))).first()[0] or 0


#: Cells of a dense product that cost no more than one product of a join.
DENSE_WORTH = 1000
#: Prefixes must save this share of the products to be worth a second join.
WORTH = 0.75


def _pruned(a: DataFrame, b: DataFrame, on: list[str], keys: tuple[str, ...], theta: float) -> DataFrame:
    """Pairs of at least theta, without a product for the others' common bins.

    Bins are ordered by how many rows they have, rare ones first. What stands from a bin on bounds what it can
    add: once the rest of a vector has a norm below theta, no pair can reach theta from there on alone. So the
    first common bin of a pair that does is in both vectors' prefixes. Prefixes meet, and the distinct candidates
    are then computed in full. Both sides and their prefixes are written once; products are
    counted first: where the vectors are dense against them, all pairs are computed by blocks, and where the
    prefixes' products are not few, all products are summed: the same pairs by the cheapest way.
    """
    group = [c for c in on if c != "bin"]
    a, b = written(a, "left"), written(b, "right")
    busy = a.select(*on).unionByName(b.select(*on)).groupBy(*on).agg(F.count(F.lit(1)).alias("_busy"))

    def prefix(side: DataFrame, entity: str, sq: str, cnt: str) -> DataFrame:
        rest = Window.partitionBy(*group, entity).orderBy(F.col("_busy").desc(), F.col("bin").desc()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        held = side.join(busy, on).withColumn("_rest", F.sum(F.col(cnt) * F.col(cnt)).over(rest))
        return written(held.where(F.col("_rest") >= theta * theta * F.col(sq) - 1e-9).select(*on, entity), "prefixes")

    left, right = prefix(a, "u", "squ", "cu"), prefix(b, "v", "sqv", "cv")
    some, products = _products(left, right, on), _products(a, b, on)
    sizes = a.groupBy(*group).agg(F.countDistinct("u").alias("_u"), F.countDistinct("bin").alias("_bins"))
    others = b.groupBy(*group).agg(F.countDistinct("v").alias("_v"))
    cells = (sizes.join(others, group) if group else sizes.crossJoin(others)).agg(F.sum(F.col("_u").cast("double") * F.col("_v") * F.col("_bins"))).first()[0] or 0.0
    if cells <= DENSE_WORTH * min(some, products):
        return blocks.grid(blocks.pack(a, b, group), group, theta=theta).select(*keys, "u", "v", "dot", "sim")
    if some > (1 - WORTH) * products:
        met = a.join(b, on)
    else:
        candidates = left.join(right, on).select(*group, "u", "v").distinct()
        met = candidates.join(a, [*group, "u"]).join(b, [*group, "bin", "v"])
    pairs = met.groupBy(*keys, "u", "v").agg(F.sum(F.col("cu") * F.col("cv")).alias("dot"), F.max("squ").alias("squ"), F.max("sqv").alias("sqv"))
    return pairs.select(*keys, "u", "v", "dot", cosine().alias("sim")).where(F.col("sim") >= theta)


def every_cosine(binned: DataFrame, left: str, right: str, labels: DataFrame | None = None, keys: tuple[str, ...] = (), salts: int = 1, hot: int = 10_000_000) -> DataFrame:
    """The pairs of ``pairwise_cosine`` by blocks of vectors: a pair is made in one task and returned from there, none is shuffled.

    salts > 1, as there, deals the left side of a group to at least so many parts where a bin of it has more than ``hot`` products.
    """
    a, b, on = _sides(binned, left, right, labels, keys)
    group = [c for c in on if c != "bin"]
    parts = salts if salts > 1 and _products(a, b, on, hot) else 1
    return blocks.grid(blocks.pack(a, b, group), group, least=(parts, 1)).select(*keys, "u", "v", "dot", "sim")


def matched_cosine(binned: DataFrame, left: str, right: str, how: str = "intersect", rule: str = "best", theta: float | None = None, m: int = 1, labels: DataFrame | None = None, keys: tuple[str, ...] = (), several: bool = False) -> DataFrame:
    """The matches of ``matching.reconcile(pairwise_cosine(...), how, rule, theta, m, keys=keys)`` without a shuffle of all pairs: blocks of vectors are multiplied in tasks that return only what may be a match."""
    a, b, on = _sides(binned, left, right, labels, keys)
    group = [c for c in on if c != "bin"]
    return blocks.matched(blocks.pack(a, b, group), group, how, rule, theta, m, keys, several)


def asked_cosine(binned: DataFrame, left: str, right: str, keys: tuple[str, ...] = ()) -> Callable[[DataFrame], DataFrame]:
    """A function that adds ``sim`` to rows with keys, u and v: only those pairs are computed, each row by its two vectors; 0 without a common bin."""
    a, b, _ = _sides(binned, left, right, None, keys)
    us = a.groupBy(*keys, "u").agg(F.collect_list(F.struct("bin", "cu")).alias("_x"), F.max("squ").alias("squ"))
    vs = b.groupBy(*keys, "v").agg(F.map_from_entries(F.collect_list(F.struct("bin", "cv"))).alias("_y"), F.max("sqv").alias("sqv"))

    def add(asked: DataFrame) -> DataFrame:
        met = asked.join(us, [*keys, "u"]).join(vs, [*keys, "v"])
        dot = F.aggregate("_x", F.lit(0).cast("long"), lambda so_far, c: so_far + c["cu"] * F.coalesce(F.try_element_at("_y", c["bin"]), F.lit(0)))
        return met.withColumn("dot", dot).withColumn("sim", cosine()).drop("_x", "_y", "squ", "sqv", "dot")

    return add


def block_cosine(vectors: DataFrame, left: str, right: str, blocks_left: int = 1, blocks_right: int = 1, min_sim: float = 0.0) -> DataFrame:
    """The same similarities by a grid of blocks: every block of one channel meets every block of the other in a task of its own.

    For dense counts over few bins; a block pair is one matrix product, a slice at a time (exact in doubles below
    2**53). The numbers of blocks are the least ones: there are as many as keep a block in a task's memory.
    """
    v = vectors.where(F.col("channel").isin(left, right))
    packed = v.select((F.col("channel") == left).alias("is_left"), F.col("entity").alias("id"), F.col("sq_norm").alias("sq"), "bins", "cnts")
    return blocks.grid(packed, [], theta=min_sim or None, least=(blocks_left, blocks_right)).select("u", "v", "dot", "sim")


def pairwise_jaccard(binned: DataFrame, left: str, right: str, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys, u, v, shared, jaccard: shared active bins over all active bins of the two. By blocks of vectors whose counts are 1; no pair is shuffled."""
    a, b, on = _sides(binned.withColumn("cnt", F.lit(1).cast("long")), left, right, None, keys)
    group = [c for c in on if c != "bin"]
    return blocks.grid(blocks.pack(a, b, group), group, measure=blocks.jaccard).select(*keys, "u", "v", F.col("dot").alias("shared"), F.col("sim").alias("jaccard"))


def near_counts(events: DataFrame, left: str, right: str, delta_us: int) -> DataFrame:
    """u, v, n: event pairs at most delta_us apart. Hard bins lose pairs across an edge; here a bin of delta_us meets itself and its neighbours, by an equi join, and the distance decides."""
    at = F.floor(F.col("us") / delta_us)
    a = events.where(F.col("channel") == left).select(F.col("src").alias("u"), F.col("us").alias("ua"), F.explode(F.array(at - 1, at, at + 1)).alias("bin"))
    b = events.where(F.col("channel") == right).select(F.col("src").alias("v"), F.col("us").alias("ub"), at.alias("bin"))
    return a.join(b, "bin").where(F.abs(F.col("ua") - F.col("ub")) <= delta_us).groupBy("u", "v").agg(F.count(F.lit(1)).alias("n"))


def last_before(events: DataFrame, left: str, right: str, entity_of_right: str = "src") -> DataFrame:
    """As-of lookup for pairs of the same id: for each event of the left channel the time of the right channel's latest event up to then (key, src, us, before_us). One window over the union, no join."""
    own = Window.partitionBy("src").orderBy("us", F.col("side").desc(), "key").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = events.where(F.col("channel").isin(left, right)).select("key", F.col(entity_of_right).alias("src"), "us", (F.col("channel") == right).cast("int").alias("side"))
    seen = rows.withColumn("before_us", F.last(F.when(F.col("side") == 1, F.col("us")), ignorenulls=True).over(own))
    return seen.where("side = 0").select("key", "src", "us", "before_us")


def channel_correlation(binned: DataFrame, spans: DataFrame) -> DataFrame:
    """left, right, corr (Pearson, over all bins of the span, empty ones too) and cos of the channels' totals per bin, for every two channels."""
    totals = binned.groupBy("channel", "bin").agg(F.sum("cnt").alias("t"))
    sums = totals.groupBy("channel").agg(F.sum("t").alias("s"), F.sum(F.col("t") * F.col("t")).alias("q"))
    x = totals.select(F.col("channel").alias("left"), "bin", F.col("t").alias("x"))
    y = totals.select(F.col("channel").alias("right"), "bin", F.col("t").alias("y"))
    products = x.join(y, "bin").where("left < right").groupBy("left", "right").agg(F.sum(F.col("x") * F.col("y")).alias("p"))
    a = sums.select(F.col("channel").alias("left"), F.col("s").alias("sx"), F.col("q").alias("qx"))
    b = sums.select(F.col("channel").alias("right"), F.col("s").alias("sy"), F.col("q").alias("qy"))
    every = F.broadcast(a).join(F.broadcast(b), F.col("left") < F.col("right")).join(products, ["left", "right"], "left").crossJoin(F.broadcast(spans.select("n_bins")))
    n, p = F.col("n_bins"), F.coalesce(F.col("p"), F.lit(0))
    cov = (n * p - F.col("sx") * F.col("sy")).cast("double")
    spread = F.sqrt((n * F.col("qx") - F.col("sx") * F.col("sx")).cast("double")) * F.sqrt((n * F.col("qy") - F.col("sy") * F.col("sy")).cast("double"))
    return every.select("left", "right", (cov / F.nullif(spread, F.lit(0.0))).alias("corr"), (p / F.sqrt((F.col("qx") * F.col("qy")).cast("double"))).alias("cos"))


def all_pairs_cosine(binned: DataFrame, labels: DataFrame | None = None, min_sim: float | None = None) -> DataFrame:
    """left, right, u, v, dot, sim for every two channels at once, by blocks of vectors: no pair is shuffled. With min_sim only pairs from there on."""
    rows = binned.withColumn("sq", F.sum(F.col("cnt") * F.col("cnt")).over(Window.partitionBy("channel", "entity")))
    on = ["bin"]
    if labels is not None:
        rows, on = rows.join(labels.select("channel", "entity", "cluster"), ["channel", "entity"]), ["cluster", "bin"]
    names = binned.select("channel").distinct()
    group = ["left", "right", *on[:-1]]
    a = rows.withColumnRenamed("channel", "left").join(F.broadcast(names.select(F.col("channel").alias("right"))), F.col("left") < F.col("right"))
    b = rows.withColumnRenamed("channel", "right").join(F.broadcast(names.select(F.col("channel").alias("left"))), F.col("left") < F.col("right"))
    a = a.select(*group, "bin", F.col("entity").alias("u"), F.col("cnt").alias("cu"), F.col("sq").alias("squ"))
    b = b.select(*group, "bin", F.col("entity").alias("v"), F.col("cnt").alias("cv"), F.col("sq").alias("sqv"))
    return blocks.grid(blocks.pack(a, b, group), group, theta=min_sim).select("left", "right", "u", "v", "dot", "sim")
