"""Jaccard join of word n-grams with Bayesian pruning of candidates.

Documents become sets of 5-word shingles (64-bit hashes; fewer than five words: one shingle of all). Documents
of equal sets form a class; everything that follows works on one document of each class, so copies cost nothing.
MinHash values are cut in bands, and classes that share a band are candidates. Connected candidates form a block,
and a block is compared in a task, or, when it holds more than a task should, in many: either every two chunks of
the block make a task, or every band value's classes do (again in chunks), whichever compares fewer pairs. A task
compares MinHash values a few at a time, drops a pair as soon as the posterior probability that its similarity
reaches the threshold falls below the tolerance, and verifies the others exactly on their sets. A pair counts if it
shares a band, and where tasks are made from band values only in its first one, so all ways find the same links.
Pairs are counted, never emitted: a task returns one row per class with its number of links and its group.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from channelalign.llm.components import connected
from channelalign.llm.memory import released
from channelalign.llm.store import written
from channelalign.llm.words import chunked, hash_grams, hashed_words, mix

WORDS = 5
THRESHOLD = 0.8
BANDS, ROWS = 60, 6
STEP = 36
TOLERANCE = 1e-7
#: What a task holds of one side of a comparison, in shingles; see _COST.
CHUNK_SHINGLES = 600_000
#: The memory of a class in a task, in shingles: its set, its text and a part for its MinHash values.
_COST = "size + bytes DIV 32 + 40"
SENT_ROWS = 1_000_000
#: Bits of the filter for each band value that classes share, and the most bits it has; it lets through what it should and, at worst, more.
FILTER_BITS = 32
MOST_BITS = 1 << 28
#: Text that is turned into sets at a time.
SLICE_BYTES = 1 << 20

_rng = np.random.default_rng(20)
_FACTORS = (_rng.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint64).astype(np.uint32)) | np.uint32(1)
_SHIFTS = _rng.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint64).astype(np.uint32)


def shingles(data: np.ndarray, offsets: np.ndarray, k: int = WORDS) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of every text."""
    words, owner = hashed_words(data, offsets)
    at, grams = hash_grams(words, owner, k)
    n = len(offsets) - 1
    bounds = np.searchsorted(owner[at], np.arange(n + 1)) if len(at) else np.zeros(n + 1, np.int64)
    sets = [np.unique(grams[bounds[i] : bounds[i + 1]]) for i in range(n)]
    counts = np.bincount(owner, minlength=n) if len(owner) else np.zeros(n, np.int64)
    first = np.cumsum(counts) - counts
    for i in np.flatnonzero((counts > 0) & (counts < k)):
        sets[i] = hash_grams(words[first[i] : first[i] + counts[i]], np.zeros(counts[i], np.int64), int(counts[i]))[1]
    return sets


def signature(values: np.ndarray) -> np.ndarray:
    """BANDS * ROWS MinHash values of one set, in slices that stay in cache."""
    low = (values >> np.uint64(17)).astype(np.uint32)
    best = np.full(len(_FACTORS), np.iinfo(np.uint32).max, np.uint32)
    for i in range(0, len(low), 512):
        part = low[None, i : i + 512] * _FACTORS[:, None]
        part ^= part >> np.uint32(15)
        part *= np.uint32(0x85EBCA6B)
        part += _SHIFTS[:, None]
        np.minimum(best, part.min(axis=1), out=best)
    return best


def bands(sig: np.ndarray) -> np.ndarray:
    """One 64-bit value for each band of one set or, row by row, of many."""
    total = np.broadcast_to(np.arange(BANDS, dtype=np.uint64) + np.uint64(1), (*sig.shape[:-1], BANDS))
    rows = sig.reshape(*sig.shape[:-1], BANDS, ROWS)
    for j in range(ROWS):
        total = mix(total ^ rows[..., j].astype(np.uint64), 1)
    return total.view(np.int64)


@lru_cache(maxsize=8)
def least_matches(threshold: float, step: int, total: int, tolerance: float) -> dict[int, int]:
    """For n compared MinHash values, the least number of matches at which P(similarity >= threshold | matches) is not below the tolerance; uniform prior, so the posterior is Beta(m + 1, n - m + 1)."""

    def tail(m: int, n: int) -> float:  # P(Beta(m+1, n-m+1) >= t) = P(Binomial(n+1, t) <= m)
        return math.fsum(math.exp(math.lgamma(n + 2) - math.lgamma(i + 1) - math.lgamma(n + 2 - i) + i * math.log(threshold) + (n + 1 - i) * math.log1p(-threshold)) for i in range(m + 1))

    return {n: next((m for m in range(n + 1) if tail(m, n) >= tolerance), n) for n in range(step, total + 1, step)}


@dataclass
class Found:
    """Links of the classes of a comparison: weight of linked documents, number of linked classes, and a group number."""

    weight: np.ndarray
    classes: np.ndarray
    group: np.ndarray
    compared: int = 0
    pruned: int = 0
    verified: int = 0


def compare(sets: list[np.ndarray], copies: np.ndarray, left: int, threshold: float = THRESHOLD, tolerance: float = TOLERANCE, same: bool = True, sigs: np.ndarray | None = None, band: int = -1) -> Found:
    """Links among the first ``left`` sets (same) or between them and the rest (not same). A pair must share a band; with ``band`` given, that must be its first."""
    n = len(sets)
    sizes = np.array([len(s) for s in sets])
    sigs = np.stack([signature(s) for s in sets]) if sigs is None else sigs
    cut = bands(sigs)
    local, ids = np.unique(np.concatenate(sets), return_inverse=True)
    begins = np.cumsum(sizes) - sizes
    least = least_matches(threshold, STEP, BANDS * ROWS, tolerance)
    found = Found(np.zeros(n, np.int64), np.zeros(n, np.int64), np.arange(n))
    mark = np.zeros(len(local), bool)

    def root(i: int) -> int:
        while found.group[i] != i:
            found.group[i] = found.group[found.group[i]]
            i = found.group[i]
        return i

    for i in range(left):
        others = np.arange(i + 1, n) if same else np.arange(left, n)
        found.compared += len(others)
        fits = np.minimum(sizes[others], sizes[i]) >= threshold * np.maximum(sizes[others], sizes[i]) - 1e-9
        alive = others[fits]
        matches = np.zeros(len(alive), np.int64)
        for done in range(STEP, BANDS * ROWS + 1, STEP):
            if not len(alive):
                break
            matches += (sigs[alive, done - STEP : done] == sigs[i, done - STEP : done]).sum(axis=1)
            stay = matches >= least[done]
            alive, matches = alive[stay], matches[stay]
        found.pruned += len(others) - len(alive)
        if len(alive):
            shared = cut[alive] == cut[i]
            alive = alive[shared.any(axis=1) & ((band < 0) | (shared.argmax(axis=1) == band))]
        found.verified += len(alive)
        if not len(alive):
            continue
        own = ids[begins[i] : begins[i] + sizes[i]]
        mark[own] = True
        at = np.repeat(begins[alive] - (np.cumsum(sizes[alive]) - sizes[alive]), sizes[alive]) + np.arange(int(sizes[alive].sum()))
        common = np.add.reduceat(mark[ids[at]].astype(np.int64), np.cumsum(sizes[alive]) - sizes[alive])
        mark[own] = False
        linked = alive[common >= threshold * (sizes[alive] + sizes[i] - common) - 1e-9]
        found.weight[i] += copies[linked].sum()
        found.classes[i] += len(linked)
        found.weight[linked] += copies[i]
        found.classes[linked] += 1
        for j in linked:
            a, b = root(i), root(int(j))
            if a != b:
                found.group[max(a, b)] = min(a, b)
    found.group = np.array([root(i) for i in range(n)])
    return found


_SKETCH = "doc_id long, tie long, k1 long, k2 long, size long, bytes long, bands array<long>"
_THINNED = _SKETCH.replace("array<long>", "array<struct<pos: int, band: long>>")


def _sketches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part, data, offsets in chunked(batches, "_text", SLICE_BYTES):
        sets = shingles(data, offsets)
        full = [len(s) > 0 for s in sets]
        keys = np.array([[np.bitwise_xor.reduce(mix(s, 3)), np.add.reduce(mix(s, 4))] if f else [0, 0] for s, f in zip(sets, full, strict=True)], np.uint64).reshape(-1, 2).view(np.int64)
        cut = [bands(signature(s)) if f else np.zeros(0, np.int64) for s, f in zip(sets, full, strict=True)]
        yield pa.RecordBatch.from_arrays(
            [
                part.column("doc_id"), part.column("tie"), pa.array(keys[:, 0]), pa.array(keys[:, 1]), pa.array([len(s) for s in sets], pa.int64()), pa.array(np.diff(offsets)),
                pa.ListArray.from_arrays(np.cumsum([0, *map(len, cut)]).astype(np.int32), np.concatenate(cut)),
            ],
            names=["doc_id", "tie", "k1", "k2", "size", "bytes", "bands"],
        )


def _signed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Adds each text's MinHash values, for texts that many tasks will read."""
    for part, data, offsets in chunked(batches, "_text", SLICE_BYTES):
        made = pa.array([signature(s).tobytes() for s in shingles(data, offsets)], pa.binary())
        yield pa.RecordBatch.from_arrays([*part.columns, made], names=[*part.schema.names, "sig"])


def _sets(texts: list[bytes]) -> list[np.ndarray]:
    """The sets of texts, a slice of them at a time."""
    out, first, held = [], 0, 0
    for n, text in enumerate(texts):
        held += len(text)
        if held > SLICE_BYTES or n + 1 == len(texts):
            own = texts[first : n + 1]
            out += shingles(np.frombuffer(b"".join(own), np.uint8), np.cumsum([0, *map(len, own)]))
            first, held = n + 1, 0
    return out


_TASK = ("block", "pos", "band", "i", "j")


def _tasks(threshold: float, tolerance: float):
    """Compares the rows of each task (block, band, left chunk, right chunk), which stand together, ordered."""

    def results(task: tuple, rows: list[tuple]):
        pos, i, j = task[1], task[3], task[4]
        own = [r for r in rows if r[0] == i]
        left = len(own)
        if i != j:
            own += [r for r in rows if r[0] == j]
        if len(own) < 2 or not left:
            return None
        sigs = np.stack([np.frombuffer(r[4], np.uint32) for r in own]) if all(r[4] for r in own) else None
        got = compare(_sets([r[3] for r in own]), np.array([r[2] for r in own], np.int64), left, threshold, tolerance, i == j, sigs, pos)
        vertex = np.array([r[1] for r in own], np.int64)
        lowest = vertex.copy()
        np.minimum.at(lowest, got.group, vertex)
        hit = got.classes > 0
        return pa.RecordBatch.from_arrays([pa.array(vertex[hit]), pa.array(lowest[got.group][hit]), pa.array(got.weight[hit]), pa.array(got.classes[hit])], names=["vertex", "linked", "weight", "classes"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = None, []
        for batch in batches:
            tasks = zip(*[batch.column(c).to_pylist() for c in _TASK], strict=True)
            numbers = zip(*[batch.column(c).to_pylist() for c in ("chunk", "vertex", "copies")], strict=True)
            for n, (task, own) in enumerate(zip(tasks, numbers, strict=True)):
                if task != held:
                    if rows and (out := results(held, rows)) is not None:
                        yield out
                    held, rows = task, []
                rows.append((*own, batch.column("_text")[n].as_py().encode("utf-8", "replace"), batch.column("sig")[n].as_py()))
        if rows and (out := results(held, rows)) is not None:
            yield out

    return run


def _split(giant: DataFrame, member: DataFrame, bound: int) -> DataFrame:
    """Tasks' rows of blocks over the bound: vertex, tie, block, pos, band, copies, chunk, chunks. giant: vertex, tie, block, copies, cost, total, many.

    Buckets of equal members (told by number and hash) are compared once, in the first of their bands: a pair of
    them shares all these bands. Of the two ways to deal a block, that of fewer pairs is taken.
    """
    cut = member.where("bands IS NOT NULL").select("vertex", "tie", F.inline("bands")).distinct()
    inside = written(giant.join(cut, ["vertex", "tie"]).select("vertex", "tie", "block", "copies", "cost", "pos", "band"), "buckets")
    sums = inside.groupBy("block", "pos", "band").agg(F.count(F.lit(1)).alias("n"), F.sum("cost").alias("of_bucket"), F.expr("bit_xor(xxhash64(vertex, tie))").alias("print"), F.min("vertex").alias("least")).where("n > 1")
    once = sums.groupBy("block", "n", "print", "least").agg(F.min(F.struct("pos", "band", "of_bucket")).alias("b")).select("block", "n", "b.*")
    once = written(once, "buckets")
    pairs = once.groupBy("block").agg(F.sum(F.col("n").cast("double") * F.col("n")).alias("pairs"))
    route = giant.select("block", "many").distinct().join(pairs, "block", "left").select("block", (F.coalesce("pairs", F.lit(0.0)) < F.col("many").cast("double") * F.col("many")).alias("by_band"))
    route = written(route, "routes")
    dealt_band = inside.join(once.join(route.where("by_band"), "block").select("block", "pos", "band", "of_bucket"), ["block", "pos", "band"]).select("vertex", "tie", "block", "pos", "band", "copies", F.ceil(F.col("of_bucket") / bound).cast("int").alias("chunks"))
    dealt_all = giant.join(route.where("NOT by_band").select("block"), "block").select("vertex", "tie", "block", F.lit(-1).alias("pos"), F.lit(0).cast("long").alias("band"), "copies", F.ceil(F.col("total") / bound).cast("int").alias("chunks"))
    return dealt_band.unionByName(dealt_all)


def _shared_bands(sketched: DataFrame) -> DataFrame:
    """The sketches with those of their bands (with their places) that two classes may share: all that are shared and few others (a bitmap of their low bits tells them)."""
    own = sketched.where("size > 0").select(F.xxhash64("k1", "k2", "size").alias("k"), F.explode("bands").alias("band"))
    shared = written(own.groupBy("band").agg(F.min("k").alias("least"), F.max("k").alias("most")).where("least < most").select("band"), "shared")
    bits = min(MOST_BITS, 1 << max(15, (FILTER_BITS * shared.count()).bit_length()))
    low = shared.select(F.col("band").bitwiseAND(F.lit(bits - 1)).alias("low"))
    words = low.groupBy(F.shiftright("low", 15).alias("at")).agg(F.bitmap_construct_agg(F.col("low").bitwiseAND(F.lit((1 << 15) - 1))).alias("word")).collect()  # at most 8192 rows of 4 KB
    table = np.zeros((bits >> 15, 1 << 12), np.uint8)
    for r in words:
        table[r["at"]] = np.frombuffer(r["word"], np.uint8)
    sent = sketched.sparkSession.sparkContext.broadcast(table.ravel())

    def thin(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column("bands")
            sizes, values = lists.value_lengths().to_numpy(), lists.flatten().to_numpy()
            at = values & (bits - 1)
            good = (sent.value[at >> 3] >> (at & 7).astype(np.uint8)) & 1 > 0
            ends = np.concatenate([[0], np.cumsum(good)])[np.concatenate([[0], np.cumsum(sizes)])]
            pos = np.arange(len(values)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
            kept = pa.ListArray.from_arrays(ends.astype(np.int32), pa.StructArray.from_arrays([pa.array(pos[good].astype(np.int32)), pa.array(values[good])], names=["pos", "band"]))
            yield pa.RecordBatch.from_arrays([kept if n == "bands" else batch.column(n) for n in batch.schema.names], names=batch.schema.names)

    return written(sketched.mapInArrow(released(thin), _THINNED), "thinned")


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, tolerance: float = TOLERANCE, chunk_shingles: int = CHUNK_SHINGLES, sent_rows: int = SENT_ROWS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, row_id, class_id, n_links, n_class_links, class_size, copies_id.

    n_links is the number of other documents with a similarity of the threshold or more, copies of this one
    included; n_class_links counts other classes of equal sets. class_id is the least id of the documents that are
    connected through links; copies_id is the least id of those with the same set; class_size counts the latter.
    Documents without words (null, empty) link to nothing and have a class each. Null ids get an id of their own
    from the text's hash (negative), which is row_id (otherwise the id itself); classes whose least ids are the same
    (an id that is repeated with another text) count as connected.

    A pair at the threshold itself is missed by all bands with probability (1 - 0.8**6)**60, about 1e-8, and by
    pruning with about the tolerance. Texts move once, for classes in a block of two or more only; those of blocks
    of more than ``chunk_shingles`` move to each of their tasks (see the module's text), so no task's memory follows
    a block's size. Band values are grouped once, and those of one class only go no further. Classes that hold more than a thousandth of all rows (so at most a thousand) are sent to the
    rows; the others are joined to them.
    """
    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    own = own.select("doc_id", F.xxhash64("_text").alias("tie"), "_text")
    known = F.coalesce(F.col("doc_id"), -F.shiftrightunsigned(F.col("tie"), 2) - 2)
    sketched = _shared_bands(written(own.mapInArrow(released(_sketches), _SKETCH), "sketches")).withColumn("vid", known)
    key = ["k1", "k2", "size"]
    classes = sketched.where("size > 0").groupBy(*key).agg(F.min(F.struct("vid", "tie")).alias("first"), F.count(F.lit(1)).alias("copies"))
    classes = written(classes.select(*key, F.col("first.vid").alias("vertex"), F.col("first.tie").alias("first_tie"), "copies"), "classes")
    large = max(1000, sketched.count() // 1000)
    hot = F.broadcast(classes.where(F.col("copies") > large))  # at most a thousand rows
    sided = sketched.join(hot, key, "left")
    cold = sided.where("vertex IS NULL").drop("vertex", "first_tie", "copies").join(classes.where(F.col("copies") <= large), key, "left")
    mine = (F.col("vid") == F.col("vertex")) & (F.col("tie") == F.col("first_tie"))
    member = sided.where("vertex IS NOT NULL").unionByName(cold).select(
        "doc_id", "vid", "tie", F.coalesce("vertex", "vid").alias("vertex"), F.coalesce("copies", F.lit(1)).alias("copies"), F.expr(_COST).alias("cost"), F.when(mine, F.col("bands")).alias("bands")
    )
    member = written(member, "members")
    band = member.where("bands IS NOT NULL").select("vertex", F.explode("bands.band").alias("band"))
    shared = band.groupBy("band").agg(F.min("vertex").alias("least"), F.max("vertex").alias("most")).where("least < most").select(F.col("band").bitwiseXOR(F.lit(1)).alias("_band"), "least")
    edges = band.join(shared, F.col("band").bitwiseXOR(F.lit(1)) == F.col("_band")).where("vertex <> least").select(F.col("vertex").alias("u"), F.col("least").alias("v")).distinct()
    vertices = member.where("bands IS NOT NULL").select("vertex", "tie", "copies", "cost").dropDuplicates(["vertex", "tie"])
    placed = written(connected(edges).withColumnRenamed("component", "block").join(vertices, "vertex"), "blocks")
    giants = written(placed.groupBy("block").agg(F.sum("cost").alias("total"), F.count(F.lit(1)).alias("many")).where(F.col("total") > chunk_shingles), "giants")
    wanted, bounded = placed.select(F.col("vertex").alias("vid"), "tie"), placed.count() <= sent_rows
    if bounded:  # checked: at most this many ids are sent to every executor
        giants, wanted = F.broadcast(giants), F.broadcast(wanted)
    small = placed.join(giants, "block", "left_anti").select("vertex", "tie", "block", F.lit(-1).alias("pos"), F.lit(0).cast("long").alias("band"), "copies", F.lit(1).alias("chunks"))
    texts = own.select(known.alias("vid"), "tie", "_text").join(wanted, ["vid", "tie"], "left_semi").dropDuplicates(["vid", "tie"]).withColumnRenamed("vid", "vertex")
    if giants.isEmpty():
        work = small.join(texts, ["vertex", "tie"]).withColumn("sig", F.lit(None).cast("binary"))
    else:
        texts = written(texts, "texts")
        split = _split(placed.join(giants, "block"), member, chunk_shingles)
        signed = texts.join(split.select("vertex", "tie").distinct(), ["vertex", "tie"], "left_semi").mapInArrow(released(_signed), "vertex long, tie long, _text string, sig binary")
        work = small.join(texts, ["vertex", "tie"]).withColumn("sig", F.lit(None).cast("binary")).unionByName(split.join(signed, ["vertex", "tie"]))
    work = work.withColumn("chunk", F.pmod(F.xxhash64("vertex", "tie"), F.col("chunks")).cast("int"))
    pair = F.explode(F.transform(F.sequence(F.lit(0), F.col("chunks") - 1), lambda x: F.struct(F.least(x, F.col("chunk")).alias("i"), F.greatest(x, F.col("chunk")).alias("j"))))
    work = work.withColumn("t", pair).select("block", "pos", "band", "t.i", "t.j", "chunk", "vertex", "copies", "_text", "sig")
    parts = work.repartition(*_TASK).sortWithinPartitions(*_TASK, "chunk", "vertex")
    linked = written(parts.mapInArrow(released(_tasks(threshold, tolerance)), "vertex long, linked long, weight long, classes long"), "links")
    links = linked.groupBy("vertex").agg(F.sum("weight").alias("weight"), F.sum("classes").alias("classes"))
    group = connected(linked.select(F.col("vertex").alias("u"), F.col("linked").alias("v"))).withColumnRenamed("component", "group")
    found = written(links.join(group, "vertex", "left"), "found")
    sent = F.broadcast(found.join(hot.select("vertex"), "vertex", "left_semi"))
    rows = member.select("doc_id", "vid", "vertex", "copies")
    joined = rows.where(F.col("copies") > large).join(sent, "vertex", "left").unionByName(rows.where(F.col("copies") <= large).join(found, "vertex", "left"))
    return joined.select(
        "doc_id",
        F.col("vid").alias("row_id"),
        F.coalesce("group", "vertex").alias("class_id"),
        (F.coalesce("weight", F.lit(0)) + F.col("copies") - 1).cast("long").alias("n_links"),
        F.coalesce("classes", F.lit(0)).cast("long").alias("n_class_links"),
        F.col("copies").cast("long").alias("class_size"),
        F.col("vertex").alias("copies_id"),
    )
