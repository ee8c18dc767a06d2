"""Token counts of a unigram vocabulary by count-only Viterbi.

An Aho-Corasick automaton over the vocabulary gives, for every end place, the pieces that end there; dynamic
programming carries the best score and the number of pieces. Ties follow the tokenizer: places are filled from
the left and a path is replaced only by a strictly better one, so of equal paths the one with the longest last
piece stays. A character that is no piece by itself may stand as unknown, at the least score minus 10, and
counts as its UTF-8 bytes (byte fallback). Scores are double precision.

A space becomes the mark U+2581 and one is put before the text, as the vocabulary's normaliser does. Where no
piece holds the mark behind another character, a text's best path is that of its words, each with the marks
before it, and each distinct word is solved once.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from channelalign.llm.memory import released

MARK = "▁"
UNKNOWN_PENALTY = 10.0
#: Parts words within a batch; texts that hold it are solved whole.
PARTING = "\x1e"
CACHE_WORDS = 300_000


class UnigramCounter:
    """Counts with the pieces and scores of a sentencepiece model file."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces = [(model.id_to_piece(i), model.get_score(i)) for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
        self._set(pieces)

    @classmethod
    def of(cls, pieces: list[tuple[str, float]]) -> UnigramCounter:
        made = cls.__new__(cls)
        made._set(pieces)
        return made

    def _set(self, pieces: list[tuple[str, float]]) -> None:
        self.scores = dict(pieces)
        self.unknown = min(self.scores.values()) - UNKNOWN_PENALTY
        self.singles = {p for p in self.scores if len(p) == 1}
        self.automaton = ahocorasick.Automaton()
        for piece, score in pieces:
            self.automaton.add_word(piece, (len(piece), score))
        self.automaton.make_automaton()
        #: Whether words can be solved apart: no piece holds the mark behind another character.
        self.apart = not any(re.search(f"[^{MARK}]{MARK}", p) for p, _ in pieces)
        self.known: dict[str, tuple[int, float]] = {}

    def solve(self, words: list[str]) -> list[tuple[int, float]]:
        """(number of tokens, score) of each text of marked characters."""
        out, matches, known = [], self.automaton.iter, self.singles.issuperset
        for text in words:
            n = len(text)
            score, count = [0.0] + [-np.inf] * n, [0] * (n + 1)
            if known(text):
                for last, (size, value) in matches(text):  # by end place, the longest first
                    total = score[last + 1 - size] + value
                    if total > score[last + 1]:
                        score[last + 1] = total
                        count[last + 1] = count[last + 1 - size] + 1
            else:
                ends: list[list[tuple[int, float]]] = [[] for _ in range(n + 1)]
                for last, found in matches(text):
                    ends[last + 1].append(found)
                for at in range(1, n + 1):
                    for size, value in ends[at]:
                        total = score[at - size] + value
                        if total > score[at]:
                            score[at], count[at] = total, count[at - size] + 1
                    if text[at - 1] not in self.singles and (total := score[at - 1] + self.unknown) > score[at]:
                        score[at], count[at] = total, count[at - 1] + len(text[at - 1].encode("utf-8", "replace"))
            out.append((count[n], score[n]))
        return out

    def count(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(tokens, score) of each text; null and empty texts have none."""
        texts = texts.cast(pa.large_string()).fill_null("")
        if not self.apart or pc.any(pc.match_substring(texts, PARTING)).as_py():
            got = self.solve([MARK + t.replace(" ", MARK) if t else "" for t in texts.to_pylist()])
            return np.array([g[0] for g in got], np.int64), np.array([g[1] for g in got], float)
        led = pc.binary_join_element_wise(pa.scalar(" ", pa.large_string()), texts, pa.scalar("", pa.large_string()))
        words = pc.split_pattern(pc.replace_substring_regex(led, "([^ ]) ", rf"\1{PARTING} "), PARTING)
        per_text = pc.list_value_length(words).to_numpy(zero_copy_only=False).astype(np.int64)
        coded = words.flatten().dictionary_encode()
        distinct = coded.dictionary.to_pylist()
        if len(self.known) > CACHE_WORDS:
            self.known.clear()
        new = [w for w in distinct if w not in self.known]
        self.known.update(zip(new, self.solve([w.replace(" ", MARK) for w in new]), strict=True))
        solved = [self.known[w] for w in distinct]
        index = coded.indices.to_numpy()
        bounds = np.concatenate([[0], np.cumsum(per_text)])
        counts = np.concatenate([[0], np.cumsum(np.array([s[0] for s in solved], np.int64)[index])])
        # A text's score is summed by itself: differences of one long sum would lose digits.
        values, owner = np.array([s[1] for s in solved], float)[index], np.repeat(np.arange(len(texts)), per_text)
        score = np.bincount(owner, values, minlength=len(texts)) if len(values) else np.zeros(len(texts))
        tokens = counts[bounds[1:]] - counts[bounds[:-1]]
        empty = pc.equal(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False)
        tokens[empty], score[empty] = 0, 0.0
        return tokens, score


@lru_cache(maxsize=4)
def counter(path: str) -> UnigramCounter:
    """One counter for each worker process and vocabulary."""
    return UnigramCounter(path)


def count_tokens(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, n_tokens, score, n_chars. Whole texts, one pass, no shuffle; null and empty texts have no tokens and score 0."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = pc.fill_null(pc.binary_length(batch.column(1)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            before = np.concatenate([[0], np.cumsum(sizes)])
            first = 0
            while first < batch.num_rows:
                last = max(first + 1, int(np.searchsorted(before, before[first] + (1 << 21), "right")) - 1)
                part = batch.slice(first, last - first)
                tokens, score = counter(model_path).count(part.column(1))
                chars = pc.fill_null(pc.utf8_length(part.column(1)), 0).cast(pa.int64())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(tokens), pa.array(score), chars], names=["doc_id", "n_tokens", "score", "n_chars"])
                first = last

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("_text")).mapInArrow(released(scan), "doc_id long, n_tokens long, score double, n_chars long")
