"""Toxic spans by a linear-chain conditional random field; marginals make document scores and offsets.

Token labels for training come from the labelled documents: a word form or word beginning that occurs far more
often in documents labelled toxic than in others marks its tokens there; every token of a document labelled
clean is clean. The field (states clean, toxic) is trained on these tokens with features of the word,
its beginnings and its end. Forward-backward marginals of a document's tokens are aggregated to a few
numbers, and a logistic model turns them into its score.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from channelalign.llm.crf import BinaryCRF, train_binary
from channelalign.llm.memory import released
from channelalign.llm.words import chunked, hash_grams, hash_words, mix, split_words

TABLE_BITS = 22
TABLE = 1 << TABLE_BITS
#: Bounds of the training sample: documents labelled toxic and clean, taken in hash order, and the longest text in bytes.
MOST_TOXIC, MOST_CLEAN, LONGEST = 1000, 2000, 32_768
FOLDS = 5
_STEMS = (4, 6)
#: Least likelihood-ratio statistic of a form that marks tokens: rare forms that met toxic documents by chance stay below.
SURE = 24.0
_BATCH = 1 << 19
_GROUP = 100


def token_features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(feature indices of each token, index of its text, start and end byte). A text contributes only what it holds itself."""
    low, a, b, owner = split_words(data, offsets)
    if not len(a):
        return np.zeros((0, 4), np.int32), owner, a, b
    word = hash_words(low, a, b)
    stems = [hash_words(low, a, np.minimum(a + n, b)) for n in _STEMS]
    tail = hash_words(low, np.maximum(b - 4, a), b)
    parts = [word, *stems, tail]
    return np.stack([(mix(p, k + 1) >> np.uint64(64 - TABLE_BITS)).astype(np.int32) for k, p in enumerate(parts)], axis=1), owner, a, b


def _firsts(owner: np.ndarray) -> np.ndarray:
    return np.concatenate([[True], owner[1:] != owner[:-1]]) if len(owner) else np.zeros(0, bool)


def document_numbers(chance: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """Aggregates of the marginals of each of n texts: constant, largest log odds, log of the expected number of toxic tokens plus one, their share, and whether the text is short."""
    clipped = np.clip(chance, 1e-7, 1 - 1e-7)
    top = np.full(n, -16.0)
    np.maximum.at(top, owner, np.log(clipped / (1 - clipped)))
    expected, words = np.bincount(owner, chance, minlength=n), np.bincount(owner, minlength=n)
    return np.stack([np.ones(n), top / 8, np.log1p(expected), np.sqrt(expected / np.maximum(words, 1)), 1 / np.sqrt(words + 1)], axis=1)


@dataclass
class ToxicityModel:
    field: BinaryCRF
    head: np.ndarray

    def __getstate__(self):
        """Weights travel as the few that training has set."""
        used = np.flatnonzero(self.field.weights).astype(np.int32)
        return used, self.field.weights[used], self.field.transition, self.field.start, self.head

    def __setstate__(self, state) -> None:
        used, values, transition, start, self.head = state
        weights = np.zeros(TABLE, np.float32)
        weights[used] = values
        self.field = BinaryCRF(weights, transition, start)

    def score(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(score of each text, chance of each token, index of its text, start and end byte)."""
        features, owner, a, b = token_features(data, offsets)
        chance = self.field.chances(features, _firsts(owner))
        numbers = document_numbers(chance, owner, len(offsets) - 1)
        return 1 / (1 + np.exp(-np.clip(numbers @ self.head, -30, 30))), chance, owner, a, b


def label_tokens(features: np.ndarray, size: int, owner: np.ndarray, toxic: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(label of each token, whether each text is of use): see the module's text. Word form and beginnings count once per document."""
    n1, n0 = max(1, int(toxic.sum())), max(1, int((~toxic).sum()))
    label = np.zeros(len(owner), bool)
    for column in range(1 + len(_STEMS)):
        seen = np.unique(owner.astype(np.int64) * size + features[:, column])
        doc, f = seen // size, seen % size
        in1, in0 = np.bincount(f[toxic[doc]], minlength=size), np.bincount(f[~toxic[doc]], minlength=size)
        share = n1 / (n1 + n0)
        one, two = in1 * np.log(np.maximum(in1, 1) / np.maximum((in1 + in0) * share, 1e-9)), in0 * np.log(np.maximum(in0, 1) / np.maximum((in1 + in0) * (1 - share), 1e-9))
        marked = (2 * (one + two) > SURE) & ((in1 + 0.1) / n1 > 12 * (in0 + 0.4) / n0)
        label |= marked[features[:, column]]
    label &= toxic[owner]
    has = np.bincount(owner[label], minlength=len(toxic)) > 0
    return label, has | ~toxic


def without_copies(texts: list[str], shared: int = 2) -> list[int]:
    """Places of texts that have fewer than this many of their eight smallest word 5-gram hashes in common with those kept before: copies of one document must not pass for independent evidence."""
    seen: set[int] = set()
    kept = []
    for i, text in enumerate(texts):
        raw = text.encode("utf-8", "replace")
        low, a, b, owner = split_words(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))
        grams = hash_grams(hash_words(low, a, b), owner, max(1, min(5, len(a))))[1]
        sketch = set(np.unique(grams)[:8].tolist())
        if len(sketch & seen) < min(shared, max(1, len(sketch))):
            kept.append(i)
        seen |= sketch
    return kept


def train(texts: list[str], toxic: list[int]) -> ToxicityModel:
    """Fits the field and the document model. With one class only, or no texts, every score is the share of that class."""
    kept = without_copies(texts)
    texts, y = [texts[i] for i in kept], np.asarray([toxic[i] for i in kept], bool)
    if not len(y) or y.all() or not y.any():
        head = np.zeros(5)
        head[0] = 0.0 if not len(y) else 4.0 if y.all() else -4.0
        return ToxicityModel(BinaryCRF(np.zeros(TABLE, np.float32), np.zeros((2, 2)), np.zeros(2)), head)
    # Texts are read in groups, so that only the tokens' feature numbers are held for all of them.
    pieces, owners = [], []
    for i in range(0, len(texts), _GROUP):
        raw = [t.encode("utf-8", "replace") for t in texts[i : i + _GROUP]]
        found, own, _, _ = token_features(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]))
        pieces.append(found)
        owners.append((own + i).astype(np.int32))
    owner, used = np.concatenate(owners), np.unique(np.concatenate([np.unique(p) for p in pieces]))
    # Training needs the weights of what it has seen only.
    features = np.concatenate([np.searchsorted(used, p).astype(np.int32) for p in pieces])
    del pieces, owners
    label, of_use = label_tokens(features, len(used), owner, y)
    parts, at = [], np.flatnonzero(of_use[owner])
    bounds = np.searchsorted(owner[at], np.arange(0, len(y) + _GROUP, _GROUP))
    for lo, hi in zip(bounds[:-1], bounds[1:], strict=True):
        if hi > lo:
            own = at[lo:hi]
            parts.append((features[own], _firsts(owner[own]), label[own].astype(float)))
    field = train_binary(parts, len(used))
    chance = field.chances(features, _firsts(owner))
    x = document_numbers(chance, owner, len(y))
    head = np.zeros(x.shape[1])
    for _ in range(60):  # Newton steps with a small ridge
        p = 1 / (1 + np.exp(-np.clip(x @ head, -30, 30)))
        slope = x.T @ (y - p) - 0.1 * head
        bend = (x * (p * (1 - p))[:, None]).T @ x + 0.1 * np.eye(x.shape[1])
        move = np.linalg.solve(bend, slope)
        head += move
        if np.abs(move).max() < 1e-8:
            break
    weights = np.zeros(TABLE, np.float32)
    weights[used] = field.weights
    return ToxicityModel(BinaryCRF(weights, field.transition, field.start), head)


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", most_toxic: int = MOST_TOXIC, most_clean: int = MOST_CLEAN) -> ToxicityModel:
    """Trains on a bounded sample of labelled rows: at most this many of each class, in hash order of the id, of texts up to LONGEST bytes. Rows with crc32(id) mod 5 = 0 and null labels are left out."""
    usable = labels.where(F.col("toxic").isNotNull() & F.col(id_col).isNotNull() & (F.crc32(F.col(id_col).cast("string")) % FOLDS != 0)).select(F.col(id_col).alias("_label_id"), F.col("toxic").cast("int").alias("_toxic"))
    order = F.xxhash64(F.col("_label_id"), F.lit(5))
    chosen = [usable.where(F.col("_toxic") == k).orderBy(order, "_label_id").limit(n) for k, n in ((1, most_toxic), (0, most_clean))]
    sample = chosen[0].unionByName(chosen[1])  # at most most_toxic + most_clean rows: safe to broadcast
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).alias("_id"), text.alias("_text")).where(F.octet_length("_text") <= LONGEST).join(F.broadcast(sample), F.col("_id") == F.col("_label_id")).select("_id", "_text", "_toxic")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        given = sorted((r["_id"], r["_text"], r["_toxic"]) for batch in batches for r in batch.to_pylist())
        yield pa.RecordBatch.from_pydict({"model": [pickle.dumps(train([t for _, t, _ in given], [y for _, _, y in given]))]})

    # The sample is bounded, so one task holds it; the driver gets the weights only.
    made = rows.repartition(1).mapInArrow(released(run), "model binary").first()
    return pickle.loads(made["model"]) if made else train([], [])


def score_toxicity(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.5, keep: tuple[str, ...] = ()) -> DataFrame:
    """One row per document: doc_id, score, predicted, spans (code-point offsets of runs of tokens with a marginal of 0.5 or more), then the columns ``keep``.

    Whole texts are scored, long ones too; nulls count as empty and get the score of a text without words.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)
    span = pa.struct([("start", pa.int64()), ("stop", pa.int64())])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in chunked(batches, "_text", _BATCH):
            score, chance, owner, a, b = sent.value.score(data, offsets)
            spans: list[list] = [[] for _ in range(part.num_rows)]
            hit = np.flatnonzero(chance >= 0.5)
            if len(hit):
                points = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])  # code points before each byte
                runs = np.split(hit, np.flatnonzero((np.diff(hit) > 1) | (owner[hit][1:] != owner[hit][:-1])) + 1)
                for run in runs:
                    d = owner[run[0]]
                    base = points[offsets[d]]
                    spans[d].append({"start": int(points[a[run[0]]] - base), "stop": int(points[b[run[-1]]] - base)})
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id"), pa.array(score), pa.array((score >= threshold).astype(np.int32)), pa.array(spans, pa.list_(span)), *[part.column(f"_kept_{c}") for c in keep]],
                names=["doc_id", "score", "predicted", "spans", *[f"_kept_{c}" for c in keep]],
            )

    schema = T.StructType([*T._parse_datatype_string("doc_id long, score double, predicted int, spans array<struct<start:long,stop:long>>").fields, *[T.StructField(f"_kept_{c}", docs.schema[c].dataType) for c in keep]])
    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"), *[F.col(c).alias(f"_kept_{c}") for c in keep])
    return own.mapInArrow(released(scan), schema).withColumnsRenamed({f"_kept_{c}": c for c in keep})


def held_out(id_col: str = "doc_id"):
    """Whether a row is kept from training."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit(""))) % FOLDS == 0
