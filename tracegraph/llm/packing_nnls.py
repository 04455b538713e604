"""Packing: non-negative least squares over shallow length combinations.

Documents are tokenised and cut into pieces of one window at most. Combinations of few lengths (four, more
only where pieces are too short for four to fill a window) are enumerated from the histogram of piece lengths; their repeat counts solve a
non-negative least squares problem against the histogram. Whole parts are taken first, then the largest fractions
are rounded up while pieces last, best filled windows before others. What is left is a smaller histogram, which is enumerated and solved again
until a round places little; the residual is packed greedily (largest piece first, then the largest that fits).

The plan works on the histogram alone, which has one number per length: it is solved on the driver, whatever the
corpus. Pieces then find their place by their rank among the pieces of their length, taken without
any task holding a whole length (``gapless_rank``); the plan's intervals, a few per length, go with the tasks.

Defined results: null text counts as empty and is the end id alone; repeated rows are packed one by one;
texts of any length are tokenised whole; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import json
import math
import re
import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import gapless_rank, materialise, store, table

#: White space so long overflows the stack of the fast encoder's pattern: the library takes such texts, with equal ids.
_LONG_SPACE = re.compile(r"\s{100000}")
#: A window is well filled from this share on.
FULL = 0.98
#: Pieces of one length that a task ranks.
RANK_ROWS = 200_000


@cache
def encoder(path: str):
    """text -> ids (numpy uint32), equal to the tokenizers library on the file, special strings included.

    The fast path is a byte-pair encoder of the tiktoken library over the same vocabulary: in this kind of file
    a token's id is its merge rank. Added tokens' strings are cut out first, as the library does; texts with
    extremely long white space take the library itself. Tests hold both against each other over the whole vocabulary and random texts.
    """
    import tiktoken
    from tokenizers import Tokenizer

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    tokens = spec.get("added_tokens", [])
    if any(t.get("lstrip") or t.get("rstrip") or t.get("single_word") for t in tokens):
        raise ValueError("added tokens that take in the text around them are not supported")
    added = {t["content"]: t["id"] for t in tokens}
    apart = re.compile("|".join(re.escape(t) for t in sorted(added, key=len, reverse=True)) or r"(?!)")
    slow = Tokenizer.from_file(path)
    import public_tokenizers

    ranks = {_bytes(t): i for t, i in spec["model"]["vocab"].items() if t not in added}
    fast = tiktoken.Encoding("file", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def encode(text: str) -> np.ndarray:
        if len(text) > 100_000 and _LONG_SPACE.search(text):
            return np.array(slow.encode(text, add_special_tokens=False).ids, np.uint32)
        out, at = [], 0
        for m in apart.finditer(text):
            out += [*fast.encode_ordinary(text[at : m.start()]), added[m.group()]]
            at = m.end()
        return np.array(out + fast.encode_ordinary(text[at:]) if out else fast.encode_ordinary(text), np.uint32)

    return encode


@cache
def _byte_of() -> dict[str, int]:
    """The printable stand-ins of byte-level vocabularies: bytes without a printable form follow from 256 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def _bytes(token: str) -> bytes:
    return bytes(_byte_of()[c] for c in token)


def pieces(docs: DataFrame, tokenizer: str, window: int, end_id: int, carry_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens (and the ids)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer)
        for batch in batches:
            out: list[list] = [[], [], [], [], [], []]
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                ids = np.append(encode(text or ""), np.uint32(end_id)).astype("<u4")
                for at in range(0, len(ids), window):
                    part = ids[at : at + window]
                    row = (doc, at, len(part), zlib.crc32(part.tobytes()), len(ids), part if carry_ids else None)
                    for column, value in zip(out, row, strict=True):
                        column.append(value)
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
            arrays = [pa.array(c, pa.int64()) for c in out[:5]]
            if carry_ids:
                names, arrays = [*names, "ids"], [*arrays, pa.array(out[5], pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(arrays, names)

    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long" + ", ids array<long>" * carry_ids
    return docs.select("doc_id", "text").mapInArrow(run, schema)


def combinations(lengths: np.ndarray, window: int, depth: int = 4) -> list[tuple[int, ...]]:
    """Combinations of at most ``depth`` of ``lengths`` that leave little of the window: each ends with the largest that fits."""
    have = np.sort(lengths)

    def fit(room: int) -> int:
        i = int(np.searchsorted(have, room, "right")) - 1
        return int(have[i]) if i >= 0 else 0

    found = set()

    def close(start: list[int]) -> None:
        combo, room = [n for n in start if n], window - sum(start)
        while len(combo) < depth and (n := fit(room)):
            combo.append(n)
            room -= n
        found.add(tuple(sorted(combo, reverse=True)))

    for first in have.tolist():
        rest = window - first
        close([first])
        for many in range(2, depth + 1 if depth > 4 else 2):  # short pieces: the rest in even parts
            combo = [first]
            while len(combo) < many and (n := fit((window - sum(combo)) // (many - len(combo)))):
                combo.append(n)
            close(combo)
        for share in (0.75, 0.5, 0.34, 0.2):
            second = fit(int(rest * share))
            if second:
                close([first, second])
                close([first, second, fit((rest - second) // 2)])
    return sorted(found, reverse=True)


def repeat_counts(combos: list[tuple[int, ...]], histogram: dict[int, int], window: int, sweeps: int = 40) -> np.ndarray:
    """Non-negative x with A x near the histogram (A: how often a combination holds a length).

    Coordinate descent, exact in each coordinate; a small price on wasted room decides between equal fits.
    """
    top = max(histogram.values())
    rest = {k: float(v) for k, v in histogram.items()}
    parts = [[(n, c.count(n)) for n in sorted(set(c))] for c in combos]
    norm = [float(sum(m * m for _, m in p)) for p in parts]
    price = [0.05 * (window - sum(c)) / window * top for c in combos]
    x = [0.0] * len(combos)
    for _ in range(sweeps):
        moved = 0.0
        for j, p in enumerate(parts):
            step = (sum(m * rest[n] for n, m in p) - price[j]) / norm[j]
            step = max(step, -x[j])
            if step:
                x[j] += step
                for n, m in p:
                    rest[n] -= m * step
                moved = max(moved, abs(step))
        if moved < max(0.25, 1e-3 * top):
            break
    return np.array(x)


class Plan:
    """What is left of a histogram, the sequences chosen so far, and how many pieces each step placed."""

    def __init__(self, histogram: dict[int, int]):
        self.rest = {k: v for k, v in histogram.items() if v}
        self.chosen: list[tuple[int, tuple[int, ...]]] = []
        self.placed = {"whole": 0, "solved": 0, "greedy": 0}

    def use(self, combo: tuple[int, ...], times: int, step: str) -> int:
        """Take ``times`` sequences of a combination, or as many as there are pieces for."""
        times = min([times, *(self.rest.get(n, 0) // combo.count(n) for n in set(combo))])
        if times > 0:
            self.chosen.append((times, combo))
            self.placed[step] += times * len(combo)
            for n in combo:
                self.rest[n] -= times
                if not self.rest[n]:
                    del self.rest[n]
        return times


def solve_round(p: Plan, window: int) -> int:
    """One round of enumeration, solution and rounding; returns how many pieces it placed."""
    pieces = sum(p.rest.values())
    if not pieces:
        return 0
    # four lengths as a rule; where pieces are so short that four leave a window half empty, as many as fill it
    depth = max(4, math.ceil(1.5 * window * pieces / sum(n * c for n, c in p.rest.items())))
    combos = [c for c in combinations(np.array(list(p.rest)), window, depth) if sum(c) >= FULL * window]
    if not combos:
        return 0
    combos.sort(key=lambda c: (window - sum(c), len(c), c))
    x = repeat_counts(combos, p.rest, window)
    before = p.placed["solved"]
    for j in np.flatnonzero(x >= 1):
        p.use(combos[j], int(x[j]), "solved")
    part = x - np.floor(x)
    for j in np.lexsort((np.arange(len(x)), -part)):
        if part[j] < 0.02:
            break
        p.use(combos[j], 1, "solved")
    return p.placed["solved"] - before


def make_plan(histogram: dict[int, int], window: int, rounds: int = 12) -> Plan:
    """Sequences that together hold every piece of the histogram once."""
    p = Plan(histogram)
    if window in p.rest:
        p.use((window,), p.rest[window], "whole")
    for _ in range(rounds):
        left = sum(p.rest.values())
        if solve_round(p, window) * 20 < left or not p.rest:
            break
    while p.rest:
        have = np.array(sorted(p.rest))
        room, combo, left = window, [], dict(p.rest)
        while have.size and (i := int(np.searchsorted(have, room, "right")) - 1) >= 0:
            n = int(have[i])
            combo.append(n)
            room -= n
            left[n] -= 1
            if not left[n]:
                have = np.delete(have, i)
        p.use(tuple(combo), min(p.rest[n] // combo.count(n) for n in set(combo)), "greedy")
    return p


def plan(histogram: dict[int, int], window: int) -> list[tuple[int, tuple[int, ...]]]:
    """(repeats, combination): together they hold every piece of the histogram once."""
    return make_plan(histogram, window).chosen


def intervals(chosen: list[tuple[int, tuple[int, ...]]]) -> tuple[np.ndarray, ...]:
    """length, low rank, pieces in a sequence, first sequence and offset of each run of ranks; sorted by the first two."""
    used: dict[int, int] = {}
    rows, sequence = [], 0
    for times, combo in chosen:
        at = 0
        for n in sorted(set(combo), reverse=True):
            m = combo.count(n)
            rows.append((n, used.get(n, 0), m, sequence, at))
            used[n] = used.get(n, 0) + m * times
            at += n * m
        sequence += times
    table_ = np.array(sorted(rows), np.int64).reshape(-1, 5)
    return tuple(table_[:, i].copy() for i in range(5))


def placed(ranked: DataFrame, chosen: list[tuple[int, tuple[int, ...]]]) -> DataFrame:
    """Pieces with their rank among those of their length -> sequence_id and offset."""
    length, low, many, first, offset = intervals(chosen)
    shift = np.int64(1 << 45)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = length * shift + low
        for batch in batches:
            n, r = batch.column("length").to_numpy(), batch.column("rank").to_numpy()
            i = np.searchsorted(keys, n * shift + r, "right") - 1
            k = r - low[i]
            names = [c for c in batch.schema.names if c != "rank"]
            columns = [batch.column(c) for c in names]
            yield pa.RecordBatch.from_arrays(
                [*columns, pa.array(first[i] + k // many[i]), pa.array(offset[i] + (k % many[i]) * n)],
                [*names, "sequence_id", "offset"],
            )

    kept = [f"{c} {t}" for c, t in ranked.dtypes if c != "rank"]
    return ranked.mapInArrow(run, ", ".join([*kept, "sequence_id long", "offset long"]))


def pack(docs: DataFrame, tokenizer: str, window: int = 2048, end_id: int = 1, carry_ids: bool = False) -> DataFrame:
    """One row per piece with its sequence and offset; sequences are padded to ``window``."""
    cut = store(pieces(docs, tokenizer, window, end_id, carry_ids), "pack-pieces")
    counts = cut.df.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()  # at most one row for each length
    chosen = plan({r["length"]: r["n"] for r in counts}, window)
    # a length's pieces are ranked in buckets of RANK_ROWS rows or so, however many there are
    buckets = max(64, math.ceil(max((r["n"] for r in counts), default=0) / RANK_ROWS))
    bucket = F.pmod(F.xxhash64("doc_id", "start"), F.lit(buckets))
    ranked = gapless_rank(cut.df, ["length"], bucket, ["doc_id", "start", "ids_crc32"], "rank")
    out = placed(ranked.select(*cut.df.columns, "rank"), chosen)
    done = materialise(out, "pack-out")
    cut.drop()
    return done


def op10_nnls_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
