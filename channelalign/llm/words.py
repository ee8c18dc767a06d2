"""Batch text helpers: byte-level word splitting and hashing without a Python loop per word.

A word is a maximal run of digits, ASCII letters (lower-cased) and non-ASCII characters, that is
``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`` after lower-casing A-Z.  UTF-8 bytes of a non-ASCII character are
all above 0x7F, so splitting bytes equals splitting characters.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 1 << 21

_LOWER = np.zeros(256, np.uint8)
_LOWER[0x30:0x3A] = np.arange(0x30, 0x3A)
_LOWER[0x61:0x7B] = np.arange(0x61, 0x7B)
_LOWER[0x41:0x5B] = np.arange(0x61, 0x7B)
_LOWER[0x80:] = np.arange(0x80, 0x100)

#: For bytes.translate: lower case, and every separator becomes a space.
SEPARATED = bytes(int(x) or 0x20 for x in _LOWER)

GRAM_BASE = np.uint64(0xD6E8FEB86659FD93)
_P = 0x9E3779B97F4A7C15
#: Bytes hashed at a time; the tables of powers are as long as this and never grow.
SPAN = 1 << 18


def _powers(base: int) -> np.ndarray:
    """base**0, base**1, ... base**SPAN modulo 2**64."""
    table = np.full(SPAN + 1, base, np.uint64)
    table[0] = 1
    return np.cumprod(table, out=table)


_POWERS, _INVERSES = _powers(_P), _powers(pow(_P, -1, 1 << 64))


def mix(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A bijective finaliser of 64-bit values (published constants of the splitmix generator)."""
    x = x + np.uint64((0x9E3779B97F4A7C15 * (seed + 1)) & (2**64 - 1))
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts of a string column, one after another, and the offsets that part them. Null is empty."""
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    raw = column.buffers()
    offsets = np.frombuffer(raw[1], np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    data = np.frombuffer(raw[2], np.uint8)[offsets[0] : offsets[-1]] if raw[2] is not None else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def chunked(batches: Iterator[pa.RecordBatch], column: str, most: int = CHUNK_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Slices of the batches with about ``most`` bytes of text each (one longer text makes a slice of its own)."""
    for batch in batches:
        data, offsets = text_buffers(batch.column(column))
        first = 0
        while first < batch.num_rows:
            last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + most, "right")) - 1)
            yield batch.slice(first, last - first), data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first]
            first = last


def split_words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(lower-cased bytes, start and end of each word, index of each word's text)."""
    low = _LOWER[data]
    inside = low > 0
    edge = np.empty(len(low) + 1, bool)
    edge[0], edge[-1] = inside[:1].any(), inside[-1:].any()
    np.not_equal(inside[1:], inside[:-1], out=edge[1:-1])
    # A word ends with its text: between two touching words of different texts stands both an end and a start.
    between = offsets[1:-1][(offsets[1:-1] > 0) & (offsets[1:-1] < len(low))]
    touching = np.unique(between[inside[between - 1] & inside[between]]) if len(between) else between
    marks = np.flatnonzero(edge)
    if len(touching):
        marks = np.sort(np.concatenate([marks, touching, touching]))
    starts, stops = marks[::2], marks[1::2]
    return low, starts, stops, np.searchsorted(offsets, starts, "right") - 1


def _hash_long(low: np.ndarray) -> np.uint64:
    """The polynomial sum of one word longer than SPAN."""
    total = np.uint64(0)
    for at in range((len(low) - 1) // SPAN * SPAN, -1, -SPAN):
        part = low[at : at + SPAN]
        with np.errstate(over="ignore"):
            total = total * _POWERS[SPAN] + (part * _POWERS[: len(part)]).sum(dtype=np.uint64)
    return total


def hash_words(low: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """A 64-bit polynomial hash of each of the given pieces (starts and stops ascend), mixed. The same bytes have the same hash wherever they stand."""
    out = np.empty(len(starts), np.uint64)
    summed = np.zeros(SPAN + 1, np.uint64)
    i = 0
    while i < len(starts):
        base = int(starts[i])
        j = int(np.searchsorted(stops, base + SPAN, "right"))
        if j <= i:
            out[i] = _hash_long(low[base : int(stops[i])])
            i += 1
            continue
        part = low[base : int(stops[j - 1])]
        np.cumsum(part * _POWERS[: len(part)], out=summed[1 : len(part) + 1])
        a, b = starts[i:j] - base, stops[i:j] - base
        out[i:j] = (summed[b] - summed[a]) * _INVERSES[a]
        i = j
    return mix(out + (stops - starts).astype(np.uint64))


def hashed_words(data: np.ndarray, offsets: np.ndarray, most: int = CHUNK_BYTES) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word, index of its text), read in pieces that end between words, so that little more than the result is held at a time."""
    words, owners, at = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], 0
    while at < len(data):
        stop = min(at + most, len(data))
        while stop < len(data) and len(gap := np.flatnonzero(_LOWER[data[stop : stop + most]] == 0)) == 0:
            stop = min(stop + most, len(data))
        stop += int(gap[0]) if stop < len(data) else 0
        low, a, b, owner = split_words(data[at:stop], np.clip(offsets, at, stop) - at)
        words.append(hash_words(low, a, b))
        owners.append(owner)
        at = stop
    return np.concatenate(words), np.concatenate(owners)


def hash_grams(words: np.ndarray, owner: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions, hashes) of all runs of k words that lie within one text."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    total = np.zeros(n, np.uint64)
    for j in range(k):
        total = total * GRAM_BASE + words[j : j + n]
    at = np.flatnonzero(owner[:n] == owner[k - 1 :])
    return at, mix(total[at], k)


def plain_words(text: str | bytes | None) -> list[bytes]:
    """The words of one text."""
    raw = text.encode("utf-8", "surrogatepass") if isinstance(text, str) else text or b""
    return raw.translate(SEPARATED).split()
