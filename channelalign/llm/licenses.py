"""Licence scan: an Aho-Corasick automaton finds notice phrases and identifier tags, a shunting-yard parser evaluates expressions."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from channelalign.llm.memory import released
from channelalign.llm.words import SEPARATED

# Phrases whose consecutive words make the base findings, and their labels.
BASE_PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}

#: Further notice phrases, as words, with label and weight in the score.
NOTICE_PHRASES = {
    "licensed under cc by nc": ("cc-by-nc", 0.9),
    "licensed under cc by sa": ("cc-by-sa", 0.9),
    "licensed under cc by": ("cc-by", 0.8),
    "creative commons attribution": ("cc-by", 0.7),
    "mozilla public license": ("mpl", 0.9),
    "lesser general public license": ("lgpl", 0.9),
    "affero general public license": ("agpl", 0.9),
    "redistribution and use in source and binary forms": ("bsd", 0.9),
    "bsd license": ("bsd", 0.8),
    "permission is hereby granted free of charge": ("mit", 0.8),
    "this is free and unencumbered software": ("unlicense", 0.9),
    "all rights reserved": ("proprietary", 0.3),
    "isc license": ("isc", 0.8),
    "boost software license": ("bsl", 0.9),
    "eclipse public license": ("epl", 0.9),
}
TAG_WORDS = "spdx license identifier"
_TAG = re.compile(r"SPDX-License-Identifier[ \t]*:[ \t]*([^\r\n]*)", re.I)
_TOKEN = re.compile(r"\(|\)|[A-Za-z0-9][A-Za-z0-9.+:-]*")
_OPERATORS = {"OR": 1, "AND": 2, "WITH": 3}


class ExpressionError(ValueError):
    """The tokens are no licence expression."""


@dataclass(frozen=True, eq=False)
class Expression:
    """An id, or an operator over two expressions. Its sets are built when they are asked for, without recursion."""

    name: str
    left: Expression | None = None
    right: Expression | None = None

    def _folded(self, leaf, join):
        """The value of the whole, from those of the ids upward."""
        steps, values, todo = [], [], [self]
        while todo:
            e = todo.pop()
            steps.append(e)
            if e.left is not None:
                todo += [e.left, e.right]
        for e in reversed(steps):
            if e.left is None:
                values.append(leaf(e.name))
            else:
                right, left = values.pop(), values.pop()
                values.append(join(e.name, left, right))
        return values[0]

    def _names(self) -> tuple[frozenset[str], frozenset[str]]:
        ids, exceptions = set(), set()
        todo = [(self, ids)]
        while todo:
            e, into = todo.pop()
            if e.left is None:
                if into is not None:
                    into.add(e.name)
            elif e.name == "WITH":
                todo += [(e.left, into), (e.right, exceptions if into is ids else None)]
            else:
                todo += [(e.left, into), (e.right, into)]
        return frozenset(ids), frozenset(exceptions)

    @property
    def ids(self) -> frozenset[str]:
        """Licence ids."""
        return self._names()[0]

    @property
    def exceptions(self) -> frozenset[str]:
        """What stands behind WITH."""
        return self._names()[1]

    @property
    def choices(self) -> frozenset[frozenset[str]]:
        """The alternatives it leaves, each a set of ids that hold together; their number can grow exponentially."""
        def join(op: str, a: frozenset, b: frozenset) -> frozenset:
            return a if op == "WITH" else a | b if op == "OR" else frozenset(x | y for x in a for y in b)

        return self._folded(lambda name: frozenset([frozenset([name])]), join)


def _family(identifier: str) -> str:
    """mit-0 and MIT become mit, Apache-2.0 apache, GPL-3.0-or-later gpl: the name before the version."""
    return re.split(r"-?\d|\+|-only|-or-later", identifier.lower(), maxsplit=1)[0].strip("-") or identifier.lower()


def parse_expression(text: str) -> Expression:
    """Operators by precedence WITH, AND, OR, left to right; parentheses group. An id alone is an expression.

    A trailing part that cannot belong to the expression (comment ends, prose) is left out: parsing stops at the
    first token that neither continues nor closes it. Raises ExpressionError if nothing can be read.
    """
    output: list[Expression] = []
    pending: list[str] = []
    expect_id = True

    def apply() -> None:
        op = pending.pop()
        if len(output) < 2:
            raise ExpressionError(f"{op} lacks an operand")
        right, left = output.pop(), output.pop()
        output.append(Expression(op, left, right))

    depth = 0
    for m in _TOKEN.finditer(text):
        token = m[0]
        op = token.upper()
        if expect_id:
            if token == "(":
                pending.append("(")
                depth += 1
            elif token == ")" or op in _OPERATORS:
                raise ExpressionError(f"{token} where a licence should be")
            else:
                output.append(Expression(token))
                expect_id = False
        elif op in _OPERATORS:
            while pending and pending[-1] != "(" and _OPERATORS[pending[-1]] >= _OPERATORS[op]:
                apply()
            pending.append(op)
            expect_id = True
        elif token == ")" and depth:
            while pending[-1] != "(":
                apply()
            pending.pop()
            depth -= 1
        else:
            break
    if expect_id or depth:
        raise ExpressionError("the expression is not complete")
    while pending:
        apply()
    if len(output) != 1:
        raise ExpressionError("nothing to read")
    return output[0]


@lru_cache(maxsize=1)
def automaton() -> ahocorasick.Automaton:
    """All phrases and the tag, as words between spaces."""
    built = ahocorasick.Automaton()
    for phrase in {*BASE_PHRASES, *NOTICE_PHRASES, TAG_WORDS}:
        built.add_word(f" {phrase} ", (phrase, phrase.count(" ") + 1))
    built.make_automaton()
    return built


def scan_text(text: str | None) -> dict:
    """Findings of one text; see scan_licenses() for the columns."""
    raw = (text or "").encode("utf-8", "replace")
    words = raw.translate(SEPARATED).split()
    joined = f" {b' '.join(words).decode('utf-8')} "
    n_base, first, last, base, labels, weight, tagged = 0, None, None, set(), set(), 0.0, False
    counted, spaces = 0, 0  # spaces before ``counted``: hits come by their ends, so every character is counted once
    for stop, (phrase, n) in automaton().iter(joined):
        if phrase in BASE_PHRASES:
            spaces, counted = spaces + joined.count(" ", counted, stop), stop
            begin = spaces - n
            n_base += 1
            first, last = begin if first is None else min(first, begin), begin if last is None else max(last, begin)
            base.add(BASE_PHRASES[phrase])
            weight = max(weight, 0.8)
        elif phrase == TAG_WORDS:
            tagged = True
        else:
            labels.add(NOTICE_PHRASES[phrase][0])
            weight = max(weight, NOTICE_PHRASES[phrase][1])
    expressions = []
    if tagged:
        for m in _TAG.finditer(text):
            try:
                found = parse_expression(m[1])
            except ExpressionError:
                continue
            expressions.append(m[1].strip())
            labels |= {_family(x) for x in found.ids}
            weight = 1.0
    return {"n_words": len(words), "n_base": n_base, "first_word": first, "last_word": last, "base_labels": ",".join(sorted(base)), "labels": ",".join(sorted(base | labels)), "score": weight, "expressions": expressions}


SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, expressions array<string>"


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, expressions.

    One pass over whole texts, no shuffle, in time linear in a text's length. Null and empty texts have no words, no
    places (null) and score 0. Rows that repeat an id are rows each; of equal texts every one has the same result.
    """

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = [("n_words", pa.int64()), ("n_base", pa.int64()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()), ("expressions", pa.list_(pa.string()))]
        for batch in batches:
            rows = [scan_text(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array([r[k] for r in rows], kind) for k, kind in types]], names=["doc_id", *[k for k, _ in types]])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("_text")).mapInArrow(released(scan), SCHEMA)
