"""License scans: ordered signature rules.

The hand-written regular expressions of ``license_pack`` run over a text's lower-cased words. A rule is tried only
where its keyword occurs. Detections are kept in order of priority; one that lies inside the
interval of a kept detection is suppressed. The base phrases keep their labels whatever happens.

One pass over each text with bounded state: no shuffle. The style is a vectorised map over Arrow batches.
Places become word numbers by one index of a text's spaces, containment by one tree of prefix maxima: time is
in proportion to the text, and to the hits times their logarithm.

Defined results: null text counts as empty: no words, no labels, score 0. Texts of any length are searched whole.
Repeated rows are judged alike; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import license_pack
from .common import table
from .shingles import plain_words

#: Phrases of the contract and their labels.
BASE = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))


@dataclass(frozen=True)
class Rule:
    label: str
    keyword: str
    pattern: re.Pattern
    confidence: float


@cache
def rules() -> tuple[Rule, ...]:
    """All rules, highest priority first. An expression begins behind a space and ends before one."""
    made = [Rule(label, keyword, re.compile(f" (?:{text})(?= )".encode()), confidence) for label, keyword, confidence, text in license_pack.lines()]
    return tuple(sorted(made, key=lambda r: -r.confidence))


@cache
def _by_keyword() -> tuple[tuple[bytes, tuple[int, ...]], ...]:
    found: dict[str, list[int]] = {}
    for i, rule in enumerate(rules()):
        found.setdefault(rule.keyword, []).append(i)
    return tuple((k.encode(), tuple(v)) for k, v in found.items())


@cache
def _gate() -> re.Pattern:
    """Matches wherever any keyword might stand: most texts end here."""
    return re.compile(b"|".join(re.escape(k) for k, _ in sorted(_by_keyword(), key=lambda x: len(x[0]))))


def normalised(text: str | None) -> bytes:
    """The words of a text, lower-cased, each between single spaces."""
    return b" " + b" ".join(plain_words(text)) + b" "


def _spaces(words: bytes) -> np.ndarray:
    """Places of the spaces: the k-th stands before word k."""
    return np.flatnonzero(np.frombuffer(words, np.uint8) == 32)


def _places(words: bytes, phrase: bytes) -> list[int]:
    """Byte places of a phrase, overlapping ones too."""
    out, at = [], words.find(phrase)
    while at >= 0:
        out.append(at)
        at = words.find(phrase, at + 1)
    return out


class _Reach:
    """How far to the right the intervals that begin at or before a place reach: a tree of prefix maxima."""

    def __init__(self, firsts: list[int]):
        self.firsts = np.unique(firsts)
        self.top = [-1] * (len(self.firsts) + 1)

    def _index(self, first: int) -> int:
        return int(np.searchsorted(self.firsts, first)) + 1

    def add(self, first: int, last: int) -> None:
        i = self._index(first)
        while i < len(self.top):
            self.top[i] = max(self.top[i], last)
            i += i & -i

    def upto(self, first: int) -> int:
        i, out = self._index(first), -1
        while i:
            out = max(out, self.top[i])
            i &= i - 1
        return out


def hits_of(words: bytes, spaces: np.ndarray) -> list[tuple[int, int, int]]:
    """(rule, first word, last word) of every match, before suppression."""
    which, begins, ends = [], [], []
    for keyword, mine in _by_keyword():
        if keyword in words:
            for i in mine:
                for m in rules()[i].pattern.finditer(words):
                    which.append(i)
                    begins.append(m.start())
                    ends.append(m.end())
    first = np.searchsorted(spaces, begins)
    last = np.searchsorted(spaces, ends) - 1
    return list(zip(which, first.tolist(), last.tolist(), strict=True))


def detect(words: bytes, spaces: np.ndarray) -> list[tuple[int, int, str, float]]:
    """(first word, last word, label, confidence) after priority and containment, by place."""
    hits = hits_of(words, spaces)
    reach = _Reach([h[1] for h in hits])
    kept: list[tuple[int, int, str, float]] = []
    # the higher confidence first, then the longer interval, then the order of the rules
    for i, first, last in sorted(hits, key=lambda h: (-rules()[h[0]].confidence, h[1] - h[2], h[0], h[1])):
        if reach.upto(first) < last:
            kept.append((first, last, rules()[i].label, rules()[i].confidence))
            reach.add(first, last)
    return sorted(kept)


SCHEMA = (
    "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string,"
    " score double, detections array<struct<first:long,last:long,label:string,confidence:double>>"
)


def scan_text(text: str | None) -> tuple:
    words = normalised(text)
    n = words.count(b" ") - 1 if words != b"  " else 0
    kept, places, base = [], [], set()
    if n and _gate().search(words):  # the base phrases hold keywords
        spaces = _spaces(words)
        for phrase, label in BASE:
            if here := _places(words, f" {phrase} ".encode()):
                places += np.searchsorted(spaces, here).tolist()
                base.add(label)
        kept = detect(words, spaces)
    labels = base | {x[2] for x in kept}
    score = max((min(1.0, x[3]) for x in kept), default=0.6 if base else 0.0)
    return (
        n,
        len(places),
        min(places, default=None),
        max(places, default=None),
        ",".join(sorted(base)),
        ",".join(sorted(labels)),
        score,
        [{"first": a, "last": b, "label": c, "confidence": d} for a, b, c, d in kept],
    )


def scan_licenses(docs: DataFrame) -> DataFrame:
    """One row per document: base phrases, labels, score and the kept detections."""
    names = ["n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "detections"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [scan_text(t) for t in batch.column("text").to_pylist()]
            columns = [batch.column("doc_id"), *[pa.array([r[i] for r in rows], TYPES[n]) for i, n in enumerate(names)]]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", *names])

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA)


TYPES = {
    "n_words": pa.int64(),
    "n_base": pa.int64(),
    "first_word": pa.int64(),
    "last_word": pa.int64(),
    "base_labels": pa.string(),
    "labels": pa.string(),
    "score": pa.float64(),
    "detections": pa.list_(
        pa.struct([("first", pa.int64()), ("last", pa.int64()), ("label", pa.string()), ("confidence", pa.float64())])
    ),
}


def op6_license_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents"))
