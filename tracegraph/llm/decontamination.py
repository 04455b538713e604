"""Benchmark decontamination: rare n-gram seeds and Smith-Waterman alignment.

1. One pass over the documents finds the n-grams they share with benchmark items, and keeps the hashed words around them.
2. Document frequencies of the benchmark's n-grams, over all documents, pick each item's seeds: n-grams rarer than a
   share of the documents and, so that widely leaked items keep some, the rarer half of every item's own.
3. Around the seeds of an item the document is aligned with the item (match +2, mismatch -1, gap -1). A document leaks
   an item when the best local score reaches ``least`` of the score of a whole copy.

Words are compared lower-cased and without punctuation.

The benchmark is a stated query set. It is read in blocks of bounded size (``BLOCK_WORDS`` words), each block goes with the tasks,
and the documents are passed once per block; nothing is joined all with all. Hits are few: no step shuffles texts.

Defined results: null or empty texts and items match nothing; an item of fewer than ``n`` words is sought as one whole sequence;
repeated rows and items are each reported; empty tables give an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import store, table
from .shingles import grams, plain_words, word_hashes

#: Words of benchmark items in a block: 8 bytes each for words and n-grams go with the tasks.
BLOCK_WORDS = 1_000_000
MATCH, MISMATCH, GAP = 2, -1, -1


class Items:
    """A block of benchmark items: words, and n-grams with their places."""

    def __init__(self, rows: list[tuple[int, str | None]], n: int):
        self.n, self.ids, self.words = n, [], []
        for item, text in rows:
            words = word_hashes(plain_words(text))
            if len(words):
                self.ids.append(item)
                self.words.append(words)
        # an item of fewer words is sought as one sequence of that length
        made = [grams(w, min(n, len(w))) for w in self.words]
        self.lengths = sorted({min(n, len(w)) for w in self.words})
        every = np.concatenate(made) if made else np.zeros(0, np.uint64)
        owner = np.repeat(np.arange(len(made)), [len(g) for g in made])
        place = np.concatenate([np.arange(len(g)) for g in made]) if made else np.zeros(0, np.int64)
        order = np.lexsort((place, owner, every))
        self.grams, self.starts = np.unique(every[order], return_index=True)
        self.starts = np.append(self.starts, len(every))
        self.owner, self.place = owner[order], place[order]
        self.longest = max(map(len, self.words), default=0)
        bits = 20
        self.shift = np.uint64(64 - bits)
        self.filter = np.zeros(1 << bits, bool)
        self.filter[self.grams >> self.shift] = True

    def find(self, made: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions in ``made`` that hold one of the n-grams, and which."""
        at = np.flatnonzero(self.filter[made >> self.shift])
        which = np.searchsorted(self.grams, made[at])
        which[which == len(self.grams)] = 0
        ok = self.grams[which] == made[at] if len(self.grams) else np.zeros(len(at), bool)
        return at[ok], which[ok]


def local_alignment(item: np.ndarray, window: np.ndarray) -> tuple[int, int]:
    """Best Smith-Waterman score of two word sequences with linear gaps, and where it ends in the window.

    Row by row; gaps along a row are a running maximum.
    """
    ramp = -GAP * np.arange(len(window) + 1)
    row = np.zeros(len(window) + 1, np.int64)
    best, end = 0, 0
    for word in item:
        fresh = np.maximum(row + GAP, 0)
        fresh[1:] = np.maximum(fresh[1:], row[:-1] + np.where(window == word, MATCH, MISMATCH))
        row = np.maximum.accumulate(fresh + ramp) - ramp
        top = int(row.argmax())
        if row[top] > best:
            best, end = int(row[top]), top
    return best, end


def _windows(at: np.ndarray, total: int, margin: int) -> list[tuple[int, int]]:
    """Stretches of a document around positions, merged where they touch."""
    out: list[list[int]] = []
    for p in at.tolist():
        a, b = max(0, p - margin), min(total, p + margin)
        if out and a <= out[-1][1]:
            out[-1][1] = max(b, out[-1][1])
        else:
            out.append([a, b])
    return [tuple(x) for x in out]


def shared_grams(docs: DataFrame, items: Items, row: str) -> DataFrame:
    """Stretches of documents around n-grams shared with the items: row, start, words (bytes), at, which."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[], [], [], [], []]
            for key, text in zip(batch.column(row).to_pylist(), batch.column("text").to_pylist(), strict=True):
                words = word_hashes(plain_words(text))
                met = [items.find(grams(words, k)) for k in items.lengths]
                at, which = (np.concatenate(x) for x in zip(*met, strict=True)) if met else (np.zeros(0, np.int64),) * 2
                order = np.argsort(at, kind="stable")
                at, which = at[order], which[order]
                if not len(at):
                    continue
                for a, b in _windows(at, len(words), 2 * items.longest):
                    inside = (at >= a) & (at < b)
                    for column, value in zip(out, (key, a, words[a:b].tobytes(), at[inside], which[inside]), strict=True):
                        column.append(value)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(out[0], pa.int64()),
                    pa.array(out[1], pa.int64()),
                    pa.array(out[2], pa.binary()),
                    pa.array(out[3], pa.list_(pa.int64())),
                    pa.array(out[4], pa.list_(pa.int64())),
                ],
                ["row", "start", "words", "at", "which"],
            )

    return docs.select(row, "text").mapInArrow(run, "row long, start long, words binary, at array<long>, which array<long>")


def seeds(items: Items, frequency: np.ndarray, documents: int, share: float) -> np.ndarray:
    """bool per place of an n-gram in an item (as in items.owner): whether it is a seed there. One sort by item and count."""
    of = np.repeat(np.arange(len(items.grams)), np.diff(items.starts))
    count = frequency[of]
    rare = count <= max(2.0, share * documents)
    if len(count):
        order = np.lexsort((count, items.owner))
        begins = np.searchsorted(items.owner[order], np.arange(len(items.ids) + 1))
        size = np.diff(begins)
        low, high = order[begins[:-1] + (size - 1) // 2], order[begins[:-1] + size // 2]
        rare |= count <= ((count[low] + count[high]) / 2)[items.owner]
    return rare


def aligned(found: DataFrame, items: Items, rare: np.ndarray, least: float) -> DataFrame:
    """row, item_id, n_seeds, score (1 for a whole copy), start and end word of the leak."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[], [], [], [], [], []]
            columns = [batch.column(c).to_pylist() for c in ("row", "start", "words", "at", "which")]
            for row, start, raw, at, which in zip(*columns, strict=True):
                words = np.frombuffer(raw, np.uint64)
                meets: dict[int, list[int]] = {}
                for p, g in zip(at, which, strict=True):
                    for k in range(items.starts[g], items.starts[g + 1]):
                        if rare[k]:
                            meets.setdefault(int(items.owner[k]), []).append(p - start - int(items.place[k]))
                for i, begins in meets.items():
                    item, size = items.words[i], len(items.words[i])
                    best = (0.0, 0, 0, 0)
                    begins.sort()
                    group = [begins[0]]
                    for b in [*begins[1:], None]:
                        if b is not None and b - group[0] <= size:
                            group.append(b)
                            continue
                        a, z = max(0, group[0] - size // 2), min(len(words), group[-1] + size + size // 2)
                        score, end = local_alignment(item, words[a:z])
                        best = max(best, (score / (MATCH * size), len(group), a + start, a + start + end))
                        group = [b]
                    if best[0] >= least:
                        for column, value in zip(out, (row, items.ids[i], best[1], best[0], best[2], best[3]), strict=True):
                            column.append(value)
            types = [pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays(
                [pa.array(c, t) for c, t in zip(out, types, strict=True)], ["row", "item_id", "n_seeds", "score", "window_start", "end"]
            )

    return found.mapInArrow(run, "row long, item_id long, n_seeds long, score double, window_start long, end long")


def benchmark_blocks(benchmark: DataFrame, n: int) -> Iterator[Items]:
    """The items in blocks of BLOCK_WORDS words at most, read one after the other; an item is never cut."""
    size, rows = 0, []
    for r in benchmark.select("item_id", "text").toLocalIterator():
        words = len(plain_words(r["text"]))
        if rows and size + words > BLOCK_WORDS:
            yield Items(rows, n)
            size, rows = 0, []
        rows.append((r["item_id"], r["text"]))
        size += words
    if rows:
        yield Items(rows, n)


def leaks(docs: DataFrame, benchmark: DataFrame, row: str = "doc_id", n: int = 4, least: float = 0.6, share: float = 0.001) -> DataFrame:
    """row, item_id, n_seeds, score, window_start and end for every document and item that it leaks."""
    total, out = docs.count(), None
    for items in benchmark_blocks(benchmark, n):
        found = store(shared_grams(docs, items, row), "leak-found").df
        counts = (
            found.select("row", F.explode("which").alias("g")).distinct().groupBy("g").agg(F.count(F.lit(1)).alias("c")).collect()
        )  # at most one row per n-gram of the block
        frequency = np.zeros(len(items.grams))
        for r in counts:
            frequency[r["g"]] = r["c"]
        part = aligned(found, items, seeds(items, frequency, total, share), least)
        out = part if out is None else out.unionByName(part)
    if out is None:
        out = docs.sparkSession.createDataFrame([], "row long, item_id long, n_seeds long, score double, window_start long, end long")
    best = F.max(F.struct("score", "n_seeds", "window_start", "end")).alias("b")
    return out.groupBy("row", "item_id").agg(best).select("row", "item_id", "b.score", "b.n_seeds", "b.window_start", "b.end")


def clean(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The rows of docs that leak no item."""
    key = F.xxhash64("doc_id", F.coalesce("text", F.lit("")))
    bad = store(leaks(docs.select(key.alias("row"), "text"), benchmark, "row", **options).select("row").distinct(), "leak-rows").df
    return docs.select(F.struct("*").alias("whole"), key.alias("row")).join(bad, "row", "left_anti").select("whole.*")


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.withColumnRenamed("row", "doc_id")
