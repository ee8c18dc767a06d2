"""Mixing sources to target weights, by fixed-length blocks of words.

The words of a source, document after document in a hash order, are cut into blocks of `block` words (the last
one may be shorter). An output shard has a fixed number of slots; how many of them each source fills is a
multinomial draw by the target weights, conditioned on the sources' whole quotas: ranges of shards are halved, and a
seed of its own draws what of a range's slots falls to its first half, so any task finds its shards' counts alone. The slots
of a source are numbered through; slot k is epoch k div n of position k mod n, and a keyed permutation of the
source's n block numbers, another one for every epoch, says which block it takes. Slots and blocks meet in a
join on (source, block). No epoch repeats a block, so a block is taken at most once more often than another,
and with targets of at most twice a source's size no document is taken more than twice.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from channelalign.llm.memory import released
from channelalign.llm.store import written
from channelalign.llm.words import mix

BLOCK = 1024
SHARE = 1.5
LIMIT = 2.0
#: The weights of the sources in order of their names, repeating.
WEIGHTS = (3, 1, 2)
SHARD_SLOTS = 1 << 14
SLOTS_A_TASK = 1 << 16
ROWS_A_BUCKET = 4096
MOST_SOURCES = 1_000_000
WORD = r"[^\x20\x09-\x0D]+"


def n_words(text: Column) -> Column:
    """Number of runs of characters other than white space."""
    spaced = F.trim(F.translate(F.coalesce(text, F.lit("")), "\t\n\x0b\x0c\r", "     "))
    return F.when(spaced == "", F.lit(0)).otherwise(F.size(F.split(spaced, " +"))).cast("long")


def targets(sizes: list[int], weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, limit: float = LIMIT) -> list[float]:
    """Each source's target: `share` of all sizes by weight; a target stops at `limit` times the source's size and the excess goes to the rest by weight, until none is above."""
    size = np.asarray(sizes, float)
    weight = np.array([weights[i % len(weights)] for i in range(len(size))], float)
    result, free, left = np.zeros(len(size)), np.ones(len(size), bool), share * size.sum()
    while free.any() and left > 0:
        given = left * weight / weight[free].sum()
        over = free & (given > limit * size)
        if not over.any():
            result[free] = given[free]
            break
        result[over] = limit * size[over]
        left -= result[over].sum()
        free &= ~over
    return result.tolist()


def permute(position: np.ndarray, n: np.ndarray, key: np.ndarray, rounds: int = 6) -> np.ndarray:
    """A keyed permutation of 0..n-1 for every row: a balanced Feistel network over the next even power of two, walked until the value is below n."""
    half = np.maximum(1, (np.ceil(np.log2(np.maximum(n, 2))).astype(np.int64) + 1) // 2).astype(np.uint64)
    half = np.where((np.uint64(1) << (half * np.uint64(2))) < n.astype(np.uint64), half + np.uint64(1), half)
    low = (np.uint64(1) << half) - np.uint64(1)
    x, todo = position.astype(np.uint64), np.ones(len(position), bool)
    key = key.astype(np.uint64)
    while todo.any():
        at = np.flatnonzero(todo)
        left, right = x[at] >> half[at], x[at] & low[at]
        for r in range(rounds):
            left, right = right, left ^ (mix(right ^ key[at], r) & low[at])
        x[at] = (left << half[at]) | right
        todo[at] = x[at] >= n[at].astype(np.uint64)
    return x.astype(np.int64)


def place_of(value: int, n: int, key: np.uint64, rounds: int = 6) -> int:
    """The position that permute() takes to ``value``: the network backwards."""
    half = max(1, (math.ceil(math.log2(max(n, 2))) + 1) // 2)
    half += (1 << 2 * half) < n
    low, x = (1 << half) - 1, value
    while True:
        left, right = x >> half, x & low
        for r in reversed(range(rounds)):
            left, right = right ^ (int(mix(np.array([left], np.uint64) ^ key, r)[0]) & low), left
        x = (left << half) | right
        if x < n:
            return x


def _epoch_keys(source: np.ndarray, epoch: np.ndarray, seed: int) -> np.ndarray:
    return mix(mix(source.astype(np.uint64), seed) ^ epoch.astype(np.uint64), seed + 1)


@dataclass
class SourcePlan:
    """What the mix takes from one source."""

    size: int
    target: float
    blocks: int
    slots: int
    trim: int  # words that the last slot takes


def plan_sources(sizes: list[int], wanted: list[float], block: int, seed: int) -> list[SourcePlan]:
    """Slots of each source, so that the taken words are the target, rounded: the last slot takes a part of its block where needed."""
    plans = []
    for s, (size, target) in enumerate(zip(sizes, wanted, strict=True)):
        n, goal = -(-size // block), min(round(target), math.floor(target + 0.5))
        if not n or not goal:
            plans.append(SourcePlan(size, target, n, 0, 0))
            continue
        short = block - (size - (n - 1) * block)  # words that the last block lacks
        full, rest = divmod(goal, size)
        slots, left = full * n, rest
        if rest:
            key = _epoch_keys(np.array([s]), np.array([full]), seed)
            place = place_of(n - 1, n, key[0])  # where the short block stands
            before = place * block
            if rest <= before:
                k, last = -(-rest // block), rest - (-(-rest // block) - 1) * block
            elif rest <= before + block - short:
                k, last = place + 1, rest - before
            else:
                beyond = rest - before - (block - short)
                k, last = place + 1 + -(-beyond // block), beyond - (-(-beyond // block) - 1) * block
            slots, left = slots + k, last
        else:
            left = block
        plans.append(SourcePlan(size, target, n, slots, left))
    return plans


def _part(rng: np.random.Generator, good: int, bad: int, n: int) -> int:
    """How many of n slots fall to ``good`` of good + bad. Beyond 10**9 slots, where the exact draw ends, a normal one of the same mean and spread."""
    if good + bad < 10**9:
        return int(rng.hypergeometric(good, bad, n)) if n else 0
    total = good + bad
    spread = math.sqrt(n * (good / total) * (bad / total) * ((total - n) / (total - 1)))
    return min(max(round(rng.normal(n * (good / total), spread)), n - bad, 0), good, n)


def draw_shards(quotas: np.ndarray, shard_slots: int, seed: int, lo: int, hi: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(shard, first slot of each source, its slots) for the shards from lo up to hi: see the module's text."""
    total = int(quotas.sum())
    todo = [(0, -(-total // shard_slots), np.zeros(len(quotas), np.int64), quotas)]
    while todo:
        a, b, first, held = todo.pop()
        if b <= lo or a >= hi:
            continue
        if b - a == 1:
            yield a, first, held
            continue
        middle = (a + b) // 2
        rng = np.random.default_rng([seed, a, b])
        n, rest = (middle - a) * shard_slots, int(held.sum())
        drawn = np.zeros(len(held), np.int64)
        for s in np.flatnonzero(held):
            rest -= int(held[s])
            drawn[s] = _part(rng, int(held[s]), rest, n)
            n -= int(drawn[s])
        todo += [(middle, b, first + drawn, held - drawn), (a, middle, first, drawn)]


@dataclass
class Mix:
    """documents: doc_id, row key, source number, size, start (words before it in its source). slots: shard, slot, source, block, epoch, words. plans by source number."""

    documents: DataFrame
    slots: DataFrame
    plans: list[SourcePlan]
    names: list[str | None]
    block: int


def mix_sources(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, limit: float = LIMIT, block: int = BLOCK, shard_slots: int = SHARD_SLOTS, seed: int = 11, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> Mix:
    """Plans the mix; see the module's text. Documents without words and null texts are sized 0 and never taken.

    Texts are read once; sizes go to a narrow table. Places of documents in their source come from sums over
    (source, bucket of rows) and running sums within a bucket, so a source that holds a third of the rows is
    spread over as many tasks as it has buckets. Only one row per source comes to the driver; more than MOST_SOURCES
    sources are refused.
    """
    spark = docs.sparkSession
    # A row is known by its id and its text's hash; rows equal in both are told apart by their place in the order.
    sized = written(
        docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("tie"), F.col(source_col).cast("string").alias("source"), n_words(F.col(text_col)).alias("size")), "sizes"
    )
    per_source = sized.groupBy("source").agg(F.sum("size").alias("size"), F.count(F.lit(1)).alias("n"))
    found = per_source.orderBy(F.col("source").asc_nulls_last()).limit(MOST_SOURCES + 1).collect()
    if len(found) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources")
    found = sorted(found, key=lambda r: (r["source"] is None, (r["source"] or "").encode("utf-8", "surrogatepass")))
    names, sizes = [r["source"] for r in found], [int(r["size"]) for r in found]
    plans = plan_sources(sizes, targets(sizes, weights, share, limit), block, seed)
    if not found:
        empty = spark.createDataFrame([], "shard long, slot long, sid int, block long, epoch long, words long")
        return Mix(sized.select("doc_id", "tie", F.lit(0).alias("sid"), "size", F.lit(0).cast("long").alias("start")), empty, plans, names, block)
    numbers = spark.createDataFrame([(i, r["source"], max(1, -(-r["n"] // ROWS_A_BUCKET))) for i, r in enumerate(found)], "sid int, source string, buckets long")
    numbered = sized.join(F.broadcast(numbers), sized["source"].eqNullSafe(numbers["source"])).select("doc_id", "tie", "sid", "size", F.pmod(F.xxhash64("doc_id", "tie", F.lit(seed)), F.col("buckets")).alias("bucket"))
    totals = numbered.groupBy("sid", "bucket").agg(F.sum("size").alias("held"))
    before = totals.select("sid", "bucket", (F.sum("held").over(Window.partitionBy("sid").orderBy("bucket")) - F.col("held")).alias("before"))
    within = Window.partitionBy("sid", "bucket").orderBy("doc_id", "tie").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    placed = numbered.withColumn("_sum", F.sum("size").over(within)).join(before, ["sid", "bucket"])
    documents = written(placed.select("doc_id", "tie", "sid", "size", (F.col("before") + F.col("_sum") - F.col("size")).alias("start")), "places")

    counts = [(p.blocks, p.slots, p.trim) for p in plans]
    quotas = np.array([p.slots for p in plans], np.int64)
    n_shards, dealt = -(-int(quotas.sum()) // shard_slots), max(1, SLOTS_A_TASK // shard_slots)

    def slots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in batch.column("id").to_pylist():
                for shard, firsts, held in draw_shards(quotas, shard_slots, seed, begin, begin + dealt):
                    for sid in np.flatnonzero(held).tolist():
                        (blocks, total, trim), first, n = counts[sid], int(firsts[sid]), int(held[sid])
                        slot = np.arange(first, first + n)
                        epoch, position = slot // blocks, slot % blocks
                        taken = permute(position, np.full(n, blocks), _epoch_keys(np.full(n, sid), epoch, seed))
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(np.full(n, shard)), pa.array(slot), pa.array(np.full(n, sid, np.int32)), pa.array(taken), pa.array(epoch), pa.array(np.where(slot == total - 1, trim, block))],
                            names=["shard", "slot", "sid", "block", "epoch", "words"],
                        )

    shards = spark.range(0, n_shards, dealt, max(1, -(-n_shards // dealt)))
    return Mix(documents, shards.mapInArrow(released(slots), "shard long, slot long, sid int, block long, epoch long, words long"), plans, names, block)


def pieces(mixed: Mix) -> DataFrame:
    """The part of every block that lies in each document: doc_id, tie, sid, size, start, block, a and b (words of the block, from a up to b). Documents without words have one row with no block."""
    b = mixed.block
    last = F.when(F.col("size") > 0, (F.col("start") + F.col("size") - 1) / b).cast("long")
    spread = mixed.documents.withColumn("block", F.explode_outer(F.when(F.col("size") > 0, F.sequence(F.floor(F.col("start") / b), last))))
    return spread.withColumns({
        "a": F.greatest(F.lit(0).cast("long"), F.col("start") - F.col("block") * b),
        "b": F.least(F.lit(b).cast("long"), F.col("start") + F.col("size") - F.col("block") * b),
    })


def taken_words(mixed: Mix) -> DataFrame:
    """One row per document: doc_id, tie, sid, size, taken (words that the mix takes from it, repeats counted)."""
    cut = F.when(F.col("words").isNull(), 0).otherwise(F.greatest(F.lit(0).cast("long"), F.least("b", "words") - F.col("a")))
    # Slots come from a function over a few rows, so their estimated size is far too small: no broadcast.
    met = pieces(mixed).join(mixed.slots.select("sid", "block", "words").hint("merge"), ["sid", "block"], "left")
    return met.groupBy("doc_id", "tie", "sid", "size", "start").agg(F.sum(cut).cast("long").alias("taken")).drop("start")


def mix_report(docs: DataFrame, **how) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, taken."""
    mixed = mix_sources(docs, **how)
    plans = docs.sparkSession.createDataFrame([(i, p.size, float(p.target)) for i, p in enumerate(mixed.plans)], "sid int, source_size long, target double")
    return taken_words(mixed).join(F.broadcast(plans), "sid").select("doc_id", "size", "source_size", "target", "taken")


def mixed_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **how) -> DataFrame:
    """The mix as documents: for every document and epoch one row with the words that the mix takes of it in that epoch, with all columns of ``docs``.

    A document taken whole keeps its text; one taken in part keeps the taken runs of words with the white space
    inside them, joined by a newline. Documents that are taken twice have two rows. Rows equal in id and text
    have a place each in the mix and share the other columns of one of them.
    """
    mixed = mix_sources(docs, id_col=id_col, text_col=text_col, source_col=source_col, **how)
    parts = pieces(mixed).where("block IS NOT NULL").join(mixed.slots.select("sid", "block", "epoch", "words").hint("merge"), ["sid", "block"])
    offset = F.col("block") * mixed.block - F.col("start")
    runs = parts.where(F.col("words") > F.col("a")).select("doc_id", "tie", "size", "start", "epoch", F.struct((offset + F.col("a")).alias("a"), (offset + F.least("b", "words")).alias("b")).alias("run"))
    kept = runs.groupBy("doc_id", "tie", "size", "start", "epoch").agg(F.array_sort(F.collect_list("run")).alias("_runs"))
    no_id = F.lit(-(2**63))
    kept = kept.select(F.coalesce("doc_id", no_id).alias("_id"), F.col("tie").alias("_tie"), F.col("size").alias("_size"), "_runs")
    names = docs.columns
    own = docs.select(*[F.col(f"`{c}`").alias(f"c_{i}") for i, c in enumerate(names)], F.coalesce(F.col(id_col).cast("long"), no_id).alias("_id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("_tie"))
    own = own.dropDuplicates(["_id", "_tie"])  # every place of equal rows is in kept
    text_at = names.index(text_col)
    schema = ", ".join(f"c_{i} {f.dataType.simpleString()}" for i, f in enumerate(docs.schema.fields))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import re

        word = re.compile(r"[^ \t\n\x0b\x0c\r]+")
        for batch in batches:
            texts = []
            for text, size, runs_of in zip(batch.column(f"c_{text_at}").to_pylist(), batch.column("_size").to_pylist(), batch.column("_runs").to_pylist(), strict=True):
                joined: list[list[int]] = []
                for run in runs_of:
                    if joined and joined[-1][1] == run["a"]:
                        joined[-1][1] = run["b"]
                    else:
                        joined.append([run["a"], run["b"]])
                if joined == [[0, size]]:
                    texts.append(text)
                    continue
                at = np.array([m.span() for m in word.finditer(text)]).reshape(-1, 2)
                texts.append("\n".join(text[at[a][0] : at[b - 1][1]] for a, b in joined))
            columns = [pa.array(texts, pa.string()) if i == text_at else batch.column(f"c_{i}") for i in range(len(names))]
            yield pa.RecordBatch.from_arrays(columns, names=[f"c_{i}" for i in range(len(names))])

    met = own.join(kept, ["_id", "_tie"]).select(*[f"c_{i}" for i in range(len(names))], "_size", "_runs")
    return met.mapInArrow(released(cut), schema).toDF(*names)
