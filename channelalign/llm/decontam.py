"""Benchmark decontamination by winnowed fingerprints.

Fingerprints of a word sequence are the minima of the k-gram hashes in every window of w consecutive k-grams
(the rightmost of equal minima). Two texts that share k + w - 1 consecutive words share a whole window and so
select the same minimum: no shared span of that length is missed. With windows of `span` words, k = 6 and
w = span - 5, the guarantee is exactly one item window. Fingerprints of documents and items are joined; each hit
is extended to the item windows around it, which are compared word by word.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from channelalign.llm.memory import released
from channelalign.llm.words import GRAM_BASE, chunked, hash_grams, hash_words, mix, plain_words, split_words

SPAN = 10
GRAM = 6
#: The most bytes of benchmark text that are sent to the executors as a whole; beyond it fingerprints meet in a shuffle.
SENT_BYTES = 16 << 20


def winnow(hashes: np.ndarray, width: int) -> np.ndarray:
    """Positions of the selected hashes of one sequence: the rightmost minimum of every window. Shorter than a window: the rightmost minimum of all."""
    if not len(hashes):
        return np.zeros(0, np.int64)
    width = min(width, len(hashes))
    windows = np.lib.stride_tricks.sliding_window_view(hashes, width)
    return np.unique(np.arange(len(windows)) + width - 1 - np.argmin(windows[:, ::-1], axis=1))


def winnow_many(at: np.ndarray, hashes: np.ndarray, owner: np.ndarray, width: int) -> np.ndarray:
    """As winnow() for k-grams of many texts one after another; indices into ``at``. Windows that would leave a text are skipped."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    best, where = hashes[width - 1 :].copy(), np.full(n, width - 1)
    for j in range(width - 2, -1, -1):
        less = hashes[j : j + n] < best
        best[less] = hashes[j : j + n][less]
        where[less] = j
    whole = at[width - 1 :] - at[:n] == width - 1
    whole &= owner[at[:n]] == owner[at[width - 1 :]]
    return np.unique((np.arange(n) + where)[whole])


@dataclass
class Windows:
    """The windows of a set of items as arrays: hash, place in the items' text and item of each, ordered by size and hash, and the fingerprints of whole windows. About 30 bytes a word beside the text."""

    span: int
    gram: int
    text: bytes  # the items' words, one space between two of an item
    ids: list
    sizes: list[int]
    keys: dict[int, np.ndarray]
    starts: dict[int, np.ndarray]
    stops: dict[int, np.ndarray]
    owners: dict[int, np.ndarray]
    prints: np.ndarray

    @property
    def width(self) -> int:
        return self.span - self.gram + 1

    @classmethod
    def of(cls, items: list[tuple], span: int = SPAN, gram: int = GRAM) -> Windows:
        """From (item id, text) rows."""
        spoken = [(item, b" ".join(words)) for item, text in items if (words := plain_words(text))]
        text = b"".join(t for _, t in spoken)
        low, a, b, owner = split_words(np.frombuffer(text, np.uint8), np.cumsum([0, *(len(t) for _, t in spoken)]))
        words = hash_words(low, a, b)
        size_of = np.minimum(np.bincount(owner, minlength=len(spoken)), span) if len(spoken) else np.zeros(0, np.int64)
        made = cls(span, gram, text, [item for item, _ in spoken], sorted(set(size_of.tolist())), {}, {}, {}, {}, np.zeros(0, np.uint64))
        for size in made.sizes:
            at, hashes = hash_grams(words, owner, size)
            own = np.flatnonzero(size_of[owner[at]] == size)
            own = own[np.argsort(hashes[own], kind="stable")]
            at = at[own]
            made.keys[size], made.starts[size], made.stops[size], made.owners[size] = hashes[own], a[at], b[at + size - 1], owner[at].astype(np.int32)
        if span in made.keys:
            at, grams = hash_grams(words, owner, gram)
            chosen = winnow_many(at, grams, owner, made.width)
            made.prints = np.unique(grams[chosen[size_of[owner[at[chosen]]] == span]])
        return made

    def items(self, size: int, hashed: np.uint64, text: bytes) -> np.ndarray:
        """Places in ``ids`` of the items that have this very window."""
        first, last = (int(np.searchsorted(self.keys[size], hashed, side)) for side in ("left", "right"))
        same = [n for n in range(first, last) if self.text[self.starts[size][n] : self.stops[size][n]] == text]
        return np.unique(self.owners[size][same])

    def candidates(self, words: np.ndarray, owner: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(size, starts, hashes) of the windows of documents whose hash is one of an item window of that size."""
        for size in self.sizes:
            if size < self.span:  # an item shorter than a window: all runs of its length are looked up
                at, grams = hash_grams(words, owner, size)
                met = _within(grams, self.keys[size])
                yield size, at[met], grams[met]
                continue
            at, grams = hash_grams(words, owner, self.gram)
            chosen = winnow_many(at, grams, owner, self.width)
            hits = at[chosen[_within(grams[chosen], self.prints)]]
            starts = np.unique((hits[:, None] - np.arange(self.width)).ravel())
            starts = starts[(starts >= 0) & (starts + size <= len(words))]
            starts = starts[owner[starts] == owner[starts + size - 1]]
            total = np.zeros(len(starts), np.uint64)
            for j in range(size):
                total = total * GRAM_BASE + words[starts + j]
            total = mix(total, size)
            met = _within(total, self.keys[size])
            yield size, starts[met], total[met]


def _within(values: np.ndarray, ordered: np.ndarray) -> np.ndarray:
    if not len(ordered):
        return np.zeros(len(values), bool)
    at = np.minimum(np.searchsorted(ordered, values), len(ordered) - 1)
    return ordered[at] == values


_RESULT = "n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, hits array<struct<start:long,stop:long>>"


def _spans(covered: np.ndarray) -> list[dict]:
    """Maximal runs of covered words."""
    edges = np.flatnonzero(np.diff(np.concatenate([[0], covered.view(np.int8), [0]])))
    return [{"start": int(a), "stop": int(b)} for a, b in edges.reshape(-1, 2)]


def _digest(items: set) -> str:
    return hashlib.sha256(",".join(sorted(map(str, items))).encode()).hexdigest()


def decontaminate(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", span: int = SPAN, sent_bytes: int = SENT_BYTES, keep: tuple[str, ...] = ()) -> DataFrame:
    """One row per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated and hits (word spans), then the columns ``keep``.

    The size of the benchmark is measured first. Up to ``sent_bytes`` of text its windows are sent to the executors
    as arrays of about six times the text's size, and documents are scanned once, without a shuffle. A larger benchmark is joined by fingerprint in a shuffle
    (see _joined). Both ways give the same rows. Null texts and texts without words hit nothing; items without
    words have no window; items of equal text are items each; null item ids count as the text 'null'.
    """
    schema = T.StructType([T.StructField("doc_id", T.LongType()), *T._parse_datatype_string(_RESULT).fields, *[T.StructField(f"_kept_{c}", docs.schema[c].dataType) for c in keep]])
    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"), *[F.col(c).alias(f"_kept_{c}") for c in keep])
    bench = benchmark.select(F.coalesce(F.col(item_col).cast("string"), F.lit("null")).alias("item"), F.coalesce(F.col(item_text_col), F.lit("")).alias("_text"))
    size = bench.agg(F.sum(F.octet_length("_text"))).first()[0] or 0
    if size <= sent_bytes:
        sent = docs.sparkSession.sparkContext.broadcast(Windows.of([(r[0], r[1]) for r in bench.collect()], span))
        result = own.mapInArrow(released(_scan(sent, span, keep)), schema)
    else:
        result = _joined(own, bench, span, keep)
    return result.withColumnsRenamed({f"_kept_{c}": c for c in keep})


def _scan(sent, span: int, keep: tuple[str, ...]):
    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        windows = sent.value  # made once, at the driver; a worker reads it once for all its tasks
        for part, data, offsets in chunked(batches, "_text"):
            low, a, b, owner = split_words(data, offsets)
            n = part.num_rows
            counts = np.bincount(owner, minlength=n)
            first = np.cumsum(counts) - counts
            covered, items = np.zeros(len(a), bool), {}
            words = hash_words(low, a, b)
            known: dict[bytes, list] = {}  # a passage that many documents share is looked up once
            for size, starts, hashes in windows.candidates(words, owner):
                for s, hashed in zip(starts.tolist(), hashes, strict=True):
                    text = b" ".join(low[a[i] : b[i]].tobytes() for i in range(s, s + size))
                    got = known.get(text)
                    if got is None:
                        got = known[text] = [windows.ids[n] for n in windows.items(size, hashed, text)]
                    if got:
                        covered[s : s + size] = True
                        items.setdefault(int(owner[s]), set()).update(got)
            hit = np.bincount(owner[covered], minlength=n)
            none = _digest(set())
            yield pa.RecordBatch.from_arrays(
                [
                    part.column(0),
                    pa.array(counts, pa.int64()),
                    pa.array(hit, pa.int64()),
                    pa.array([len(items.get(i, ())) for i in range(n)], pa.int64()),
                    pa.array([_digest(items[i]) if i in items else none for i in range(n)], pa.string()),
                    pa.array(hit > 0),
                    pa.array([_spans(covered[first[i] : first[i] + counts[i]]) if hit[i] else [] for i in range(n)], pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))),
                    *[part.column(f"_kept_{c}") for c in keep],
                ],
                names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "hits", *[f"_kept_{c}" for c in keep]],
            )

    return scan


def _joined(own: DataFrame, bench: DataFrame, span: int, keep: tuple[str, ...]) -> DataFrame:
    """The same result for a benchmark of any size: fingerprints of both sides meet in a shuffle, and so do the windows around each hit.

    Rows are numbered by (id, hash of the text), so repeated ids stay apart; equal rows share their hits. Only
    texts with a hit come back for the comparison of whole windows, which joins window texts for equality.
    """
    gram, width = GRAM, span - GRAM + 1
    sizes = sorted(r[0] for r in bench.select(F.least(F.size(F.regexp_extract_all(F.col("_text"), F.lit("[0-9A-Za-z\\x{80}-\\x{10FFFF}]+"), F.lit(0))), F.lit(span)).alias("n")).where("n > 0").distinct().collect())

    def prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in chunked(batches, "_text"):
            low, a, b, owner = split_words(data, offsets)
            words = hash_words(low, a, b)
            out = []
            for size in sizes:
                at, grams = hash_grams(words, owner, gram if size == span else size)
                if size == span:
                    chosen = winnow_many(at, grams, owner, width)
                    at, grams = at[chosen], grams[chosen]
                out.append((size, owner[at], grams))
            key = part.column("_key")
            yield pa.RecordBatch.from_arrays(
                [key.take(pa.array(np.concatenate([o for _, o, _ in out]) if out else np.zeros(0, np.int64))), pa.array(np.concatenate([np.full(len(o), s, np.int32) for s, o, _ in out]) if out else np.zeros(0, np.int32)), pa.array(np.concatenate([g.view(np.int64) for _, _, g in out]) if out else np.zeros(0, np.int64))],
                names=["_key", "size", "gram"],
            )

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, starts, found, lengths = [], [], [], []
            for key, text in zip(batch.column("_key").to_pylist(), batch.column("_text").to_pylist(), strict=True):
                words = plain_words(text)
                for size in sizes:
                    for i in range(len(words) - size + 1):
                        keys.append(key), starts.append(i), lengths.append(size), found.append(b" ".join(words[i : i + size]).decode("utf-8", "replace"))
                if len(keys) > 50_000:
                    yield pa.RecordBatch.from_pydict({"_key": keys, "start": starts, "size": pa.array(lengths, pa.int32()), "window": found})
                    keys, starts, found, lengths = [], [], [], []
            yield pa.RecordBatch.from_pydict({"_key": pa.array(keys, pa.string()), "start": pa.array(starts, pa.int64()), "size": pa.array(lengths, pa.int32()), "window": pa.array(found, pa.string())})

    def item_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, found, lengths = [], [], []
            for key, text in zip(batch.column("item").to_pylist(), batch.column("_text").to_pylist(), strict=True):
                words = plain_words(text)
                size = min(span, len(words))
                for i in range(len(words) - size + 1 if size else 0):
                    keys.append(key), lengths.append(size), found.append(b" ".join(words[i : i + size]).decode("utf-8", "replace"))
            yield pa.RecordBatch.from_pydict({"item": pa.array(keys, pa.string()), "size": pa.array(lengths, pa.int32()), "window": pa.array(found, pa.string())})

    keyed = own.withColumn("_key", F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.sha2("_text", 256)))
    texts = keyed.select("_key", "_text")
    wanted = bench.mapInArrow(released(item_windows), "item string, size int, window string")
    item_prints = wanted.select(F.col("window").alias("_key"), F.col("window").alias("_text"), F.col("size").alias("_own")).distinct().select("_key", "_text").mapInArrow(released(prints), "_key string, size int, gram long").select("size", "gram").distinct()
    doc_prints = texts.mapInArrow(released(prints), "_key string, size int, gram long").distinct()
    near = doc_prints.join(item_prints, ["size", "gram"], "left_semi").select("_key").distinct()
    met = texts.join(near, "_key", "left_semi").distinct().mapInArrow(released(windows), "_key string, start long, size int, window string")
    by_window = wanted.groupBy("size", "window").agg(F.array_sort(F.collect_set("item")).alias("items"))
    hits = met.join(by_window, ["size", "window"])
    covered = hits.select("_key", F.explode(F.sequence("start", F.col("start") + F.col("size") - 1)).alias("word")).distinct().groupBy("_key").agg(F.count(F.lit(1)).alias("n_hit"), F.array_sort(F.collect_list("word")).alias("_words"))
    items = hits.select("_key", "items").distinct().groupBy("_key").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("_items"))
    n_words = F.size(F.regexp_extract_all(F.col("_text"), F.lit("[0-9A-Za-z\\x{80}-\\x{10FFFF}]+"), F.lit(0))).cast("long")
    begins = F.filter("_words", lambda w: ~F.array_contains("_words", w - 1))
    ends = F.filter("_words", lambda w: ~F.array_contains("_words", w + 1))
    spans = F.zip_with(begins, ends, lambda a, b: F.struct(a.alias("start"), (b + 1).alias("stop")))
    none = F.array().cast("array<struct<start:bigint,stop:bigint>>")
    found = keyed.join(covered, "_key", "left").join(items, "_key", "left")
    return found.select(
        "doc_id", n_words.alias("n_words"), F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"),
        F.when(F.col("_items").isNull(), 0).otherwise(F.size("_items")).cast("long").alias("n_items"),
        F.sha2(F.array_join(F.coalesce("_items", F.array().cast("array<string>")), ","), 256).alias("items_sha256"),
        (F.coalesce("n_hit", F.lit(0)) > 0).alias("contaminated"),
        F.when(F.col("_words").isNull(), none).otherwise(spans).alias("hits"),
        *[F.col(f"_kept_{c}") for c in keep],
    )


SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(w[i : i + least(len(w), 10) - 1], ' ') AS k
  FROM (SELECT item_id, w, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS i FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, n, i, array_to_string(w[i : i + n - 1], ' ') AS k
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, sizes WHERE len(w) >= n)),
h AS (SELECT doc_id, i, n, item_id FROM dw JOIN bw USING (n, k)),
c AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM (SELECT DISTINCT doc_id, i, n FROM h)) GROUP BY doc_id),
x AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM h) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (doc_id) LEFT JOIN x USING (doc_id)
"""
