"""Token ids in files of independent zstandard frames with a trailing seek table.

File layout: data frames, then one skippable frame with the document index, then one skippable frame with the
seek table. A data frame holds the ids of whole documents as little-endian unsigned 32-bit integers, about
FRAME_IDS of them (one longer document fills a frame alone), and can be decompressed alone. The seek table has
the compressed size, the decompressed size and the xxHash64 checksum (low 32 bits) of every frame. The document
index has (id, number of ids) of every document in order, so a reader finds the frame and the place of a
document and decompresses that frame only.
"""

from __future__ import annotations

import os
import re
import uuid
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from channelalign.llm.memory import released
from channelalign.llm.store import fresh_dir, written

# Fixed values of the public seekable format: magic numbers, and the descriptor bit that says checksums are present.
SKIPPABLE_SEEK = 0x184D2A5E
SEEKABLE_MAGIC = 0x8F92EAB1
CHECKSUM_FLAG = 0x80

SKIPPABLE_INDEX = 0x184D2A50
INDEX_MAGIC = b"DOCINDEX"
FRAME_IDS = 1 << 16
NULL_ID = -(2**63)
CACHE_WORDS = 300_000
WORDS_AT_ONCE = 512
#: A character that parts words on their way through the tokenizer; words that hold it go alone.
PARTING = "~"
#: A letter of Latin-1 (the same in composed form) and ASCII punctuation after it.
LETTER_THEN_MARK = r"([a-z\x{C0}-\x{D6}\x{D8}-\x{F6}\x{F8}-\x{FF}])([!-/:-@\[-`{-~])"
#: A special token's beginning, or a mark that may join the letter before it.
RISKY = r"<\||[\x{300}-\x{36f}]"
#: Words of these are one piece for the tokenizer's model, which marks a piece's last token where it has a suffix for that.
_LETTERS = re.compile("[a-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+").fullmatch
_SPACE = re.compile(r"[ \t\n\x0b\x0c\r]")


# ---------------------------------------------------------------- encoding

class WordEncoder:
    """Encodes texts with a tokenizer of the tokenizers library, each distinct word once.

    For tokenizers that lower-case, drop white space, never let a token span it and part letters from punctuation
    (their pre-tokenizer removes or splits it, their normaliser works on characters). Then the ids of a text are
    those of its words, one after another. Texts are lower-cased (A-Z) and parted at ASCII white space and between
    a Latin letter and ASCII punctuation; texts that may hold a special token or a combining mark, where this
    could change what the tokenizer sees, are parted at white space only. The cache is bounded.
    """

    def __init__(self, path: str, cache: int = CACHE_WORDS):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer, self.most = Tokenizer.from_file(path), cache
        mark = self.tokenizer.encode(PARTING, add_special_tokens=False).ids
        self.mark = mark[0] if len(mark) == 1 else None
        suffix = getattr(self.tokenizer.model, "end_of_word_suffix", None)
        self.last = np.array([(self.tokenizer.id_to_token(i) or "").endswith(suffix) for i in range(self.tokenizer.get_vocab_size())]) if suffix else None
        self._clear()

    def _clear(self) -> None:
        self.known: dict[str, int] = {}
        self.starts, self.pool, self.used = np.zeros(1 << 16, np.int64), np.zeros(1 << 18, np.uint32), 0

    def _each(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        ids = [e.ids for e in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]
        return np.fromiter(chain.from_iterable(ids), np.uint32), np.fromiter(map(len, ids), np.int64, len(ids))

    def _ids(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words, one after another, and how many each has. Words go to the tokenizer joined by a mark, which has an id of its own, and are parted at that id."""
        if self.mark is not None:
            joined = f" {PARTING} ".join(words)
            if joined.count(PARTING) == len(words) - 1:
                ids = np.asarray(self.tokenizer.encode_batch_fast([joined], add_special_tokens=False)[0].ids, np.uint32)
                cuts = np.flatnonzero(ids == self.mark)
                if len(cuts) == len(words) - 1:
                    return ids[ids != self.mark], np.diff(cuts, prepend=-1, append=len(ids)) - 1
        return self._each(words)

    def _of_letters(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """As _ids, for words of letters: without marks, parted after each last token."""
        ids = np.asarray(self.tokenizer.encode_batch_fast([" ".join(words)], add_special_tokens=False)[0].ids, np.uint32)
        ends = np.flatnonzero(self.last[ids])
        if len(ends) == len(words) and ends[-1] == len(ids) - 1:
            return ids, np.diff(ends, prepend=-1)
        return self._ids(words)

    def _learn(self, words: list[str]) -> None:
        plain, marked = [w for w in words if PARTING not in w], [w for w in words if PARTING in w]
        if self.last is not None:
            letters, plain = [w for w in plain if _LETTERS(w)], [w for w in plain if not _LETTERS(w)]
            for i in range(0, len(letters), WORDS_AT_ONCE):
                self._keep(letters[i : i + WORDS_AT_ONCE], *self._of_letters(letters[i : i + WORDS_AT_ONCE]))
        for i in range(0, len(plain), WORDS_AT_ONCE):
            self._keep(plain[i : i + WORDS_AT_ONCE], *self._ids(plain[i : i + WORDS_AT_ONCE]))
        if marked:
            self._keep(marked, *self._each(marked))

    def _keep(self, words: list[str], ids: np.ndarray, sizes: np.ndarray) -> None:
        first, total = len(self.known), self.used + int(sizes.sum())
        while len(self.starts) < first + len(words) + 1:
            self.starts = np.concatenate([self.starts, np.zeros_like(self.starts)])
        while len(self.pool) < total:
            self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
        self.pool[self.used : total] = ids
        self.starts[first + 1 : first + 1 + len(words)] = self.used + np.cumsum(sizes)
        self.known.update(zip(words, range(first, first + len(words)), strict=True))
        self.used = total

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, one after another; number of ids of each text). texts: large_string without nulls."""
        parted = pc.replace_substring_regex(pc.ascii_lower(texts), LETTER_THEN_MARK, r"\1 \2")
        risky = pc.match_substring_regex(texts, RISKY)
        if pc.any(risky).as_py():
            parted = pc.if_else(risky, texts, parted)
        words = pc.ascii_split_whitespace(parted)
        per_text = pc.list_value_length(words).to_numpy(zero_copy_only=False).astype(np.int64)
        coded = words.flatten().dictionary_encode()
        if not len(coded):
            return np.zeros(0, np.uint32), np.zeros(len(texts), np.int64)
        distinct = coded.dictionary.to_pylist()
        new = [w for w in distinct if w not in self.known]
        if len(self.known) + len(new) > self.most and self.known:
            self._clear()
            new = distinct
        self._learn(new)
        at = np.fromiter(map(self.known.__getitem__, distinct), np.int64, len(distinct))
        code, begin, size = coded.indices.to_numpy(), self.starts[at], self.starts[at + 1] - self.starts[at]
        each = size[code]
        before = np.concatenate([[0], np.cumsum(each)])
        ids = self.pool[np.repeat(begin[code] - before[:-1], each) + np.arange(int(before[-1]))]
        bounds = before[np.concatenate([[0], np.cumsum(per_text)])]
        return ids, np.diff(bounds)


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    """One encoder for each worker process."""
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


def _cut(text: str, most: int) -> list[str]:
    """The text in pieces of about ``most`` characters, cut at white space."""
    pieces, at = [], 0
    while at < len(text):
        gap = _SPACE.search(text, at + most)
        stop = gap.start() if gap else len(text)
        pieces.append(text[at:stop])
        at = stop
    return pieces


def encode_texts(texts: pa.Array, path: str, end_id: int, most: int = 1 << 21) -> Iterator[np.ndarray]:
    """The ids of each text and its end id. Texts are taken to about ``most`` bytes at a time; a longer text is encoded in pieces."""
    coder = encoder(path)
    texts = texts.cast(pa.large_string()).fill_null("")
    offsets = np.concatenate([[0], np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False))]).astype(np.int64) if len(texts) else np.zeros(1, np.int64)
    first, end = 0, np.array([end_id], np.uint32)
    while first < len(texts):
        last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + most, "right")) - 1)
        part = texts.slice(first, last - first)
        if last - first == 1 and offsets[last] - offsets[first] > 2 * most:
            yield np.concatenate([*[coder.encode(pa.array([x], pa.large_string()))[0] for x in _cut(part[0].as_py(), most)], end])
        else:
            ids, sizes = coder.encode(part)
            at = 0
            for n in sizes.tolist():
                yield np.concatenate([ids[at : at + n], end])
                at += n
        first = last


# ---------------------------------------------------------------- file format

class SeekableWriter:
    """Writes documents to a binary stream, frame by frame."""

    def __init__(self, out, frame_ids: int = FRAME_IDS, level: int = 3):
        self.out, self.frame_ids = out, frame_ids
        self.packer = zstandard.ZstdCompressor(level=level, write_checksum=False)
        self.entries: list[tuple[int, int, int]] = []
        self.docs: list[tuple[int, int]] = []
        self.waiting: list[np.ndarray] = []
        self.n_waiting = 0

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        if self.n_waiting and self.n_waiting + len(ids) > self.frame_ids:
            self._frame()
        self.docs.append((NULL_ID if doc_id is None else doc_id, len(ids)))
        self.waiting.append(ids.astype("<u4"))
        self.n_waiting += len(ids)

    def _frame(self) -> None:
        raw = b"".join(x.tobytes() for x in self.waiting)
        packed = self.packer.compress(raw)
        self.out.write(packed)
        self.entries.append((len(packed), len(raw), xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF))
        self.waiting, self.n_waiting = [], 0

    def close(self) -> None:
        if self.n_waiting:
            self._frame()
        index = zstandard.ZstdCompressor(level=3).compress(np.array(self.docs, "<i8").reshape(-1, 2).tobytes())
        body = INDEX_MAGIC + index
        self._skippable(SKIPPABLE_INDEX, body)
        entries = [*self.entries, (8 + len(body), 0, 0)]  # the index frame is in the table, with nothing to decompress
        table = np.array(entries, "<u4").reshape(-1, 3).tobytes()
        self._skippable(SKIPPABLE_SEEK, table + len(entries).to_bytes(4, "little") + bytes([CHECKSUM_FLAG]) + SEEKABLE_MAGIC.to_bytes(4, "little"))

    def _skippable(self, magic: int, body: bytes) -> None:
        self.out.write(magic.to_bytes(4, "little") + len(body).to_bytes(4, "little") + body)


class SeekableReader:
    """Reads documents of one file; decompresses only the frames that hold them and checks each frame's checksum."""

    def __init__(self, source):
        self.source = source
        size = source.seek(0, 2)
        tail = self._read(size - 9, 9)
        if int.from_bytes(tail[5:], "little") != SEEKABLE_MAGIC or not tail[4] & CHECKSUM_FLAG:
            raise ValueError("no seek table with checksums at the end of the file")
        n = int.from_bytes(tail[:4], "little")
        at = size - 9 - 12 * n
        head = self._read(at - 8, 8)
        if int.from_bytes(head[:4], "little") != SKIPPABLE_SEEK or int.from_bytes(head[4:], "little") != 12 * n + 9:
            raise ValueError("the seek table is damaged")
        self.table = np.frombuffer(self._read(at, 12 * n), "<u4").reshape(-1, 3).astype(np.int64)
        self.starts = np.cumsum(self.table[:, 0]) - self.table[:, 0]
        index = self._read(int(self.starts[-1]) + 8, int(self.table[-1, 0]) - 8)
        if index[: len(INDEX_MAGIC)] != INDEX_MAGIC:
            raise ValueError("the document index is damaged")
        docs = np.frombuffer(zstandard.ZstdDecompressor().decompress(index[len(INDEX_MAGIC) :]), "<i8").reshape(-1, 2)
        self.doc_ids, self.sizes = docs[:, 0], docs[:, 1]
        self.begins = np.cumsum(self.sizes) - self.sizes
        self.frame_begins = (np.cumsum(self.table[:-1, 1]) - self.table[:-1, 1]) // 4
        self.frames_read = 0
        self._held: tuple[int, np.ndarray] | None = None

    def _read(self, at: int, n: int) -> bytes:
        self.source.seek(at)
        return self.source.read(n)

    def frame(self, k: int) -> np.ndarray:
        if self._held is None or self._held[0] != k:
            packed, unpacked, checksum = map(int, self.table[k])
            raw = zstandard.ZstdDecompressor().decompress(self._read(int(self.starts[k]), packed), max_output_size=unpacked)
            if len(raw) != unpacked or xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != checksum:
                raise ValueError(f"frame {k} is damaged")
            self.frames_read += 1
            self._held = k, np.frombuffer(raw, "<u4")
        return self._held[1]

    def document(self, position: int) -> np.ndarray:
        """The ids of the document at this position of the file."""
        k = int(np.searchsorted(self.frame_begins, self.begins[position], "right")) - 1
        at = int(self.begins[position] - self.frame_begins[k])
        return self.frame(k)[at : at + int(self.sizes[position])]

    def find(self, doc_id: int) -> list[np.ndarray]:
        """The ids of every document with this id."""
        return [self.document(int(i)) for i in np.flatnonzero(self.doc_ids == doc_id)]


# ---------------------------------------------------------------- Spark

def _filesystem(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (pafs.LocalFileSystem(), uri)


SHARD_SCHEMA = "shard long, path string, n_docs long, n_ids long"
DOC_SCHEMA = "doc_id long, shard long, position long, offset long, n_tokens long, ids_crc32 long"


def write_token_files(docs: DataFrame, folder: str, tokenizer_path: str, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encodes every text, writes shard files in ascending id order (null ids first) and returns one row per file.

    The rows are range-partitioned by id, so the files in order hold ascending ids and no task sees more than its
    range. A task writes under a name of its own and renames at the end; a task that runs again writes the same
    content under the same final name, so lost executors and speculative copies leave whole files only.
    """

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard = TaskContext.get().partitionId()
        fs, base = _filesystem(folder)
        path, temporary = f"{base}/part-{shard:08d}.tok.zst", f"{base}/.part-{shard:08d}-{uuid.uuid4().hex}"
        counts = [0, 0]
        with fs.open_output_stream(temporary) as out:
            writer = SeekableWriter(out)
            for batch in batches:
                for doc_id, ids in zip(batch.column(0).to_pylist(), encode_texts(batch.column(1), tokenizer_path, end_id), strict=True):
                    writer.add(doc_id, ids)
                    counts[0] += 1
                    counts[1] += len(ids)
            writer.close()
        fs.move(temporary, path)
        yield pa.RecordBatch.from_pydict({"shard": [shard], "path": [f"{folder}/part-{shard:08d}.tok.zst"], "n_docs": [counts[0]], "n_ids": [counts[1]]})

    fs, base = _filesystem(folder)
    fs.create_dir(base, recursive=True)
    tied = F.xxhash64(text_col)
    ordered = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).repartitionByRange(F.col("doc_id")).sortWithinPartitions("doc_id", tied if text_col == "text" else F.xxhash64("text"))
    return written(ordered.mapInArrow(released(write), SHARD_SCHEMA), "token-shards")


def read_token_files(shards: DataFrame) -> DataFrame:
    """One row per document of these files: its id, file, position, place in the file and the CRC-32 of its ids."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, path in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                fs, base = _filesystem(path)
                with fs.open_input_file(base) as source:
                    reader = SeekableReader(source)
                    for first in range(0, len(reader.sizes), 8192):
                        part = slice(first, first + 8192)
                        sums = [zlib.crc32(reader.document(i).tobytes()) for i in range(first, min(first + 8192, len(reader.sizes)))]
                        ids = reader.doc_ids[part]
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(ids, pa.int64(), mask=ids == NULL_ID), pa.array([shard] * len(sums), pa.int64()), pa.array(np.arange(first, first + len(sums))), pa.array(reader.begins[part]), pa.array(reader.sizes[part]), pa.array(sums, pa.int64())],
                            names=["doc_id", "shard", "position", "offset", "n_tokens", "ids_crc32"],
                        )

    tasks = max(1, min(shards.count(), 1 << 14))  # a fixed number, so that these few small rows are not gathered in one task
    return shards.select("shard", "path").repartition(tasks).mapInArrow(released(read), DOC_SCHEMA)


def token_output(docs: DataFrame, tokenizer_path: str, end_id: int = 1, folder: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Writes the token files and returns what reading them back gives: doc_id, start, n_tokens, ids_crc32, path, position.

    start counts the ids of all documents before this one over all files. Null texts are empty: they hold the end
    id only. Repeated ids keep a row each, ordered by a hash of their text. Empty tables give no rows.
    """
    spark = docs.sparkSession
    shards = write_token_files(docs, folder or fresh_dir(spark, "tokens"), tokenizer_path, end_id, id_col, text_col)
    # One row per file: a running sum over them by a join of each file with those before it would be quadratic, a window is not.
    from pyspark.sql import Window

    before = F.sum("n_ids").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))
    starts = shards.select("shard", "path", F.coalesce(before, F.lit(0)).cast("long").alias("_before"))
    return read_token_files(shards).join(F.broadcast(starts), "shard").select(
        "doc_id", (F.col("_before") + F.col("offset")).alias("start"), "n_tokens", "ids_crc32", "path", "position"
    )
