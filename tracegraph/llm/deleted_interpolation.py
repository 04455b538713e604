"""LM scoring: deleted interpolation.

A word bigram model. Its probability is a mixture of maximum-likelihood estimates

    p(w|v) = l2(b) c(v,w)/c(v) + l1(b) c(w)/N + l0(b) 1/(V+1)

with weights for each bucket b of the context's frequency (octaves of c(v)). Training documents are split again: one
fold is held out from the counts, and the weights are learned on it by expectation-maximisation; final scores
use the counts of all training documents.

Counts of n-grams grow with the corpus and never reach the driver or a broadcast. They are exchanged in packed form:

1. Texts become batches of about ``BATCH_TOKENS`` tokens (written once): words as numbers of the batch, and each word's hash.
2. Each batch sends its distinct n-grams with counts to key ranges; the number of ranges follows the corpus.
3. Each range adds up, and answers each batch with the totals of the keys that it sent, in their order.
4. Batches of the held-out fold meet their answers: a histogram (bucket, quantised estimates) of bounded size gives the
   weights. Then all batches meet theirs, and score.

A hot word or copied text is counted inside the batches before anything is sent. N-grams are told apart by hashes of 48 bits
and the bits of the range.

Defined results: null text counts as empty, its only token is the end; a null doc_id has the fold of an empty one; without training tokens every token has the uniform
share; repeated rows are trained on and scored one by one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, store, table
from .shingles import mix, word_hashes, words_of

BATCH_TOKENS = 1_000_000
RANGE_TOKENS = 2_000_000
#: Hashes that no word has but by accident: the end of a text, and the context of its first word.
END, BEGIN = np.uint64(0x0E4D0E4D0E4D0E4D), np.uint64(0xBE61BE61BE61BE61)
FOLDS, TEST, HELD = 7, 2, 3
#: Stands for a null doc_id in a batch.
NO_ID = -(1 << 63)
BUCKETS, STEPS = 24, 4


def tokenised(docs: DataFrame) -> DataFrame:
    """Rows of about BATCH_TOKENS tokens: batch, held (the fold for the weights), doc ids, folds, sizes, tokens, words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, made = TaskContext.get().partitionId(), 0
        open_: dict[bool, list] = {False: [], True: []}
        tokens = {False: 0, True: 0}

        def close(held: bool) -> pa.RecordBatch:
            nonlocal made
            rows, open_[held], tokens[held] = open_[held], [], 0
            sizes = np.array([len(r[2]) for r in rows], np.int32)
            words, index = np.unique(np.concatenate([r[2] for r in rows]), return_inverse=True)
            made += 1
            values = [
                [(part << 32) | made],
                [held],
                [int(sizes.sum())],
                [np.array([NO_ID if r[0] is None else r[0] for r in rows], np.int64).tobytes()],
                [np.array([r[1] for r in rows], np.uint8).tobytes()],
                [sizes.tobytes()],
                [_squeezed(index.astype(np.uint32).tobytes())],
                [words.tobytes()],
            ]
            types = [pa.int64(), pa.bool_(), pa.int64(), *[pa.binary()] * 5]
            names = ["batch", "held", "n_tokens", "docs", "folds", "sizes", "tokens", "words"]
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(values, types, strict=True)], names)

        for batch in batches:
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                fold = zlib.crc32(b"" if doc is None else str(doc).encode()) % FOLDS
                row = np.append(word_hashes(words_of(text)), END)
                held = fold == HELD
                open_[held].append((doc, fold, row))
                tokens[held] += len(row)
                if tokens[held] >= BATCH_TOKENS:
                    yield close(held)
        for held in (False, True):
            if open_[held]:
                yield close(held)

    schema = "batch long, held boolean, n_tokens long, docs binary, folds binary, sizes binary, tokens binary, words binary"
    return docs.select("doc_id", "text").mapInArrow(run, schema)


class Batch:
    """A batch with its keys: every distinct word, and every distinct pair of neighbours."""

    def __init__(self, row: dict):
        view = lambda name, kind: np.frombuffer(row[name], kind)
        self.docs, self.folds, self.sizes = view("docs", np.int64), view("folds", np.uint8), view("sizes", np.int32)
        self.word, words = np.frombuffer(_opened(row["tokens"]), np.uint32), view("words", np.uint64)
        self.first = np.concatenate([[0], np.cumsum(self.sizes)[:-1]]).astype(np.int64)
        hashes = words[self.word]
        before = np.roll(hashes, 1)
        before[self.first] = BEGIN
        # the word before each token; the end stands in for the beginning: both occur once in a text
        self.context = np.roll(self.word, 1)
        self.context[self.first] = np.searchsorted(words, END)
        self.pairs, self.pair = np.unique(mix(before * np.uint64(0x9E3779B97F4A7C15) + mix(hashes)), return_inverse=True)
        self.singles = mix(words + np.uint64(1))
        self.order = np.argsort(self.singles)
        self.words = words

    def fold_of_tokens(self) -> np.ndarray:
        return np.repeat(self.folds, self.sizes)


def _squeezed(data: bytes) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(data)


def _opened(data: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(data)


def _packed(counts: np.ndarray) -> bytes:
    """Counts as a byte each, and the few that need more behind them."""
    big = np.flatnonzero(counts >= 255)
    small = np.minimum(counts, 255).astype(np.uint8)
    return _squeezed(np.int64(len(counts)).tobytes() + big.astype(np.int64).tobytes() + counts[big].astype(np.int64).tobytes() + small.tobytes())


def _unpacked(data: bytes) -> np.ndarray:
    raw = _opened(data)
    n = int(np.frombuffer(raw, np.int64, 1)[0])
    out = np.frombuffer(raw, np.uint8, n, len(raw) - n).astype(np.int64)
    index, values = np.frombuffer(raw[8 : len(raw) - n], np.int64).reshape(2, -1)
    out[index] = values
    return out


def _short(keys: np.ndarray) -> bytes:
    """The low 48 bits of sorted keys, high bytes first: those change slowly and cost little."""
    return _squeezed(np.ascontiguousarray(keys.astype("<u8").view(np.uint8).reshape(-1, 8)[:, 5::-1].T).tobytes())


def _long(data: bytes) -> np.ndarray:
    raw = np.frombuffer(_opened(data), np.uint8).reshape(6, -1)
    out = np.zeros((raw.shape[1], 8), np.uint8)
    out[:, :6] = raw[::-1].T
    return out.view("<u8").reshape(-1)


def _cuts(keys: np.ndarray, bits: int) -> np.ndarray:
    """Where each range begins in sorted keys, and the end."""
    edges = (np.arange(1 << bits, dtype=np.uint64) << np.uint64(64 - bits)) if bits else np.zeros(1, np.uint64)
    return np.append(np.searchsorted(keys, edges), len(keys))


def sent_counts(batches: DataFrame, bits: int) -> DataFrame:
    """Rows (range, batch, keys, main, held): what each batch has of each key range. Words take the upper ranges."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for got in rows:
            for row in got.to_pylist():
                b = Batch(row)
                fold = b.fold_of_tokens()
                main, held = (fold != TEST) & (fold != HELD), fold == HELD
                out: list[list] = [[], [], [], [], []]
                for base, keys, index, n in (
                    (0, b.pairs, b.pair, len(b.pairs)),
                    (1 << bits, b.singles[b.order], b.word, len(b.singles)),
                ):
                    counts = [np.bincount(index[m], minlength=n) for m in (main, held)]
                    if base:
                        counts = [c[b.order] for c in counts]
                    cuts = _cuts(keys, bits)
                    for r, (a, z) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                        if a < z:
                            values = (base + r, row["batch"], _short(keys[a:z]), _packed(counts[0][a:z]), _packed(counts[1][a:z]))
                            for column, value in zip(out, values, strict=True):
                                column.append(value)
                types = [pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary()]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(c, t) for c, t in zip(out, types, strict=True)], ["range", "batch", "keys", "main", "held"]
                )

    return batches.mapInArrow(run, "range int, batch long, keys binary, main binary, held binary")


def answered(sent: DataFrame, bits: int) -> DataFrame:
    """Rows (batch, range, main, held): totals of the keys that a batch sent; and a row of sums per range (batch null)."""

    def run(key, group):
        r = key[0].as_py()
        keys = [_long(x) for x in group.column("keys").to_pylist()]
        main = np.concatenate([_unpacked(x) for x in group.column("main").to_pylist()])
        held = np.concatenate([_unpacked(x) for x in group.column("held").to_pylist()])
        all_, index = np.unique(np.concatenate(keys), return_inverse=True)
        total = [np.bincount(index, c, len(all_)).astype(np.int64) for c in (main, held)]
        cuts = np.concatenate([[0], np.cumsum([len(k) for k in keys])])
        parts = [[_packed(t[index[a:z]]) for a, z in zip(cuts[:-1], cuts[1:], strict=True)] for t in total]
        words = r >= 1 << bits
        both = total[0] + total[1]
        sums = [int(x) * words for x in (total[0].sum(), both.sum(), (total[0] > 0).sum(), (both > 0).sum())]
        n = len(keys)
        columns = {
            "batch": pa.array([*group.column("batch").to_pylist(), None], pa.int64()),
            "range": pa.array([r] * (n + 1), pa.int32()),
            "main": pa.array([*parts[0], None], pa.binary()),
            "held": pa.array([*parts[1], None], pa.binary()),
        }
        for name, value in zip(("n_main", "n_all", "v_main", "v_all"), sums, strict=True):
            columns[name] = pa.array([None] * n + [value], pa.int64())
        return pa.table(columns)

    schema = "batch long, range int, main binary, held binary, n_main long, n_all long, v_main long, v_all long"
    return sent.groupBy("range").applyInArrow(run, schema)


def _estimates(row: dict, answers: pa.Table, bits: int, with_held: bool):
    """The batch, and per token: count of the word, of its context and of both together."""
    b = Batch(row)
    ranges = answers.column("range").to_numpy()
    order = np.argsort(ranges)
    main, held = answers.column("main").to_pylist(), answers.column("held").to_pylist()
    got = [_unpacked(main[i]) + (_unpacked(held[i]) if with_held else 0) for i in order]
    is_word = ranges[order] >= 1 << bits
    gather = lambda which: np.concatenate([g for g, w in zip(got, is_word, strict=True) if w == which])
    pairs, singles = gather(False), np.empty(len(b.singles), np.int64)
    singles[b.order] = gather(True)
    if len(pairs) != len(b.pairs):
        raise ValueError("answers don't fit their batch")
    return b, singles[b.word], singles[b.context], pairs[b.pair]


def _bucket(context: np.ndarray) -> np.ndarray:
    return np.minimum(np.log2(context + 1.0).astype(np.int64), BUCKETS - 1)


def _ratio(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.divide(a, b, out=np.zeros(len(a)), where=b > 0)


def held_histogram(batches: DataFrame, answers: DataFrame, bits: int, n: int) -> DataFrame:
    """bucket, q2, q1 (quantised octaves of the two estimates, null for zero) and number of held-out tokens."""

    def quantised(p: np.ndarray) -> np.ndarray:
        return np.where(p > 0, np.round(np.log2(np.where(p > 0, p, 1.0)) * STEPS), 1).astype(np.int64)

    def run(key, left, right):
        b, word, context, both = _estimates(left.to_pylist()[0], right, bits, False)
        bucket, q2, q1 = _bucket(context), quantised(_ratio(both, context)), quantised(word / max(n, 1))
        rows, count = np.unique(np.stack([bucket, q2, q1], 1), axis=0, return_counts=True)
        return pa.table({"bucket": rows[:, 0], "q2": rows[:, 1], "q1": rows[:, 2], "n": count.astype(np.int64)})

    joined = batches.groupBy("batch").cogroup(answers.groupBy("batch"))
    made = joined.applyInArrow(run, "bucket long, q2 long, q1 long, n long")
    return made.groupBy("bucket", "q2", "q1").agg(F.sum("n").alias("n"))


def learn_weights(histogram: list[tuple[int, int, int, int]], uniform: float, rounds: int = 60) -> np.ndarray:
    """Weights (l2, l1, l0) per bucket by expectation-maximisation; each starts with one token's worth of evidence."""
    weights = np.full((BUCKETS, 3), 1 / 3)
    if not histogram:
        return weights
    h = np.array(histogram, float)
    bucket, n = h[:, 0].astype(int), h[:, 3]
    p = np.stack([np.where(h[:, i] > 0, 0.0, 2.0 ** (h[:, i] / STEPS)) for i in (1, 2)] + [np.full(len(h), uniform)], 1)
    for _ in range(rounds):
        share = weights[bucket] * p
        share *= (n / share.sum(1))[:, None]
        total = np.stack([np.bincount(bucket, share[:, i], BUCKETS) for i in range(3)], 1) + 1 / 3
        weights = total / total.sum(1, keepdims=True)
    return np.maximum(weights, 1e-6)


def scored(batches: DataFrame, answers: DataFrame, bits: int, n: int, v: int, weights: np.ndarray) -> DataFrame:
    uniform = 1.0 / (v + 1)

    def run(key, left, right):
        b, word, context, both = _estimates(left.to_pylist()[0], right, bits, True)
        w = weights[_bucket(context)]
        p = w[:, 0] * _ratio(both, context) + w[:, 1] * (word / max(n, 1)) + w[:, 2] * uniform
        add = lambda x: np.add.reduceat(x, b.first)
        return pa.table(
            {
                "doc_id": pa.array(b.docs, mask=b.docs == NO_ID),
                "held_out": b.folds == TEST,
                "n_tokens": b.sizes.astype(np.int64),
                "n_known": add((word > 0).astype(np.int64)),
                "train_tokens": np.full(len(b.docs), n, np.int64),
                "base_score": add(np.log10((word + 1.0) / (n + v + 1.0))),
                "score": add(np.log10(p)),
            }
        )

    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    return batches.groupBy("batch").cogroup(answers.groupBy("batch")).applyInArrow(run, schema)


def score_documents(docs: DataFrame) -> DataFrame:
    """One row per document: its base score and its log10 probability under the interpolated model."""
    batches = materialise(tokenised(docs), "lm-batches")
    total = batches.agg(F.sum("n_tokens")).first()[0] or 0
    bits = min(16, max(2, math.ceil(math.log2(max(1, total) / RANGE_TOKENS + 1)) + 1))
    found = store(answered(sent_counts(batches, bits), bits), "lm-answers")
    sums = found.df.where("batch is null").agg(*[F.sum(c).alias(c) for c in ("n_main", "n_all", "v_main", "v_all")]).first()
    n_main, n_all, v_main, v_all = (x or 0 for x in sums)
    answers = found.df.where("batch is not null").select("batch", "range", "main", "held")
    held = batches.where("held")
    mine = answers.join(held.select("batch"), "batch", "left_semi")
    histogram = held_histogram(held, mine, bits, n_main).collect()  # bounded: buckets times quantised estimates
    weights = learn_weights([tuple(r) for r in histogram], 1.0 / (v_main + 1))
    return scored(batches, answers, bits, n_all, v_all, weights)


def op4_deleted_interpolation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(table(spark, sf_dir, "documents"))
