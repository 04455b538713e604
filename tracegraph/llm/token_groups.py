"""N-gram Jaccard join through a token-group matrix.

Documents with equal shingle sets become one class. Similar classes are partitioned into groups, and each group stores the
union of its members' tokens. A query class that shares a key with a group is measured against that
union, and the group is opened, its members compared with the query, only if the overlap can reach the threshold.

Keys come in two kinds. By default they are MinHash bands, as many that a pair at the threshold shares none with probability
``miss``, 1e-10, at most. With ``exact`` they are prefix tokens, and no link can be lost: with tokens in one order for all, sets x and y that share o
tokens or more share l of them among the first |x| - o + l of x and |y| - o + l of y. Here o is ceil(p |x|), the least overlap of x with any
partner, and l a twelfth of |x| (``spare``). The order is by frequency, rare first, then by hash; any order is exact, so frequencies only
need to be good where they are high (``frequent_shingles``). Sentences from a common stock bring prefix tokens
together whose number of pairs grows faster than the corpus, which is why bands are the default.

1. One pass over the texts: size, digest and keys of each shingle set. Keys are exchanged packed, by ranges; those of one class alone go no
   further. A key and its classes are a bucket.
2. Classes are compared with the pivots of their buckets where they share enough of them: links found give components. This only thins what follows.
3. Classes of buckets that still hold several components are partitioned into clusters: a large component, or else
   the classes whose largest such buckets lead to one (two hops). A cluster is dealt into groups of ``GROUP`` members or ``GROUP_TOKENS`` tokens or so.
   The token-group matrix has a row for each key and cluster. Of two components the smaller asks: a class meets the matrix rows of its keys, and asks the
   groups of a cluster if they share as many keys as it shares with a linked member at least, and those only where sizes allow a link.
   What lies inside one component is not asked: it can't change the result.
4. A group that is asked is measured whole: the asker's overlap with the union of all members' tokens bounds its overlap with each, and
   only where that reaches the threshold are the members compared. Askers of a group are dealt into blocks, so a task holds
   a group and a block whatever their numbers.
5. Components by repeated minimum labels over the links, one written table a round.

Every reported link is exact. Sets are only shipped for classes that ask or are asked.

Defined results: documents without words or text have no shingles, are linked with nothing and are their own component;
repeated rows and equal texts share a class; a repeated doc_id is one node for all its rows' classes only if they link.
A null doc_id counts as larger than any other: a component of such rows alone has a null name.
An empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, store, table
from .shingles import mix, shingle_set

#: Hash functions of a band.
ROWS = 4
#: Members of a group, and askers in a block, and their tokens: about, as they are dealt by hash. A task holds one of either.
GROUP, GROUP_TOKENS = 1024, 1 << 20
#: Rows that one task makes of a key's askers and what is offered to them.
PAIRS = 1_000_000
#: Shingles that are ordered by their frequency, at most: 16 bytes each go with the tasks. The others are ordered by hash.
MOST_FREQUENT = 1_000_000
#: Shingles of a window of documents, and how often one must occur in a window to be counted.
WINDOW_TOKENS, SEEN = 8_000_000, 2
#: Stands for a null doc_id: larger than any other.
NO_ID = (1 << 63) - 1
#: Prefix tokens in a range of the exchange, about.
RANGE_TOKENS = 2_000_000
_ODD = np.uint64(0x9E3779B97F4A7C15)


def frequent_shingles(docs: DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The most frequent shingles, sorted, and their counts; over all documents, as far as they are frequent in some window."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, known = [], 0, set()

        def flush() -> pa.RecordBatch:
            token, count = np.unique(np.concatenate(held), return_counts=True) if held else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
            often = count >= SEEN
            return pa.RecordBatch.from_arrays([pa.array(token[often].view(np.int64)), pa.array(count[often].astype(np.int64))], ["token", "c"])

        for batch in batches:
            for text in batch.column("text").to_pylist():
                tokens = shingle_set(text, n)
                digest = int(tokens.sum(dtype=np.uint64))
                if digest in known:  # a copy: the class counts once
                    continue
                known.add(digest)
                held.append(tokens)
                size += len(tokens)
                if size >= WINDOW_TOKENS:
                    yield flush()
                    held, size, known = [], 0, set()
        yield flush()

    counted = docs.select("text").mapInArrow(run, "token long, c long").groupBy("token").agg(F.sum("c").alias("c"))
    top = counted.orderBy(F.desc("c"), "token").limit(MOST_FREQUENT).toArrow()
    token, count = top.column("token").to_numpy().view(np.uint64), top.column("c").to_numpy()
    order = np.argsort(token)
    return token[order], count[order]


def spare(n: int) -> int:
    """How many prefix tokens a set of ``n`` shares at least with a linked one of the same size; never less for larger sets."""
    return max(1, n // 12)


def _spare(n: str) -> str:
    return f"greatest(1, {n} div 12)"


def _one(n: str) -> str:
    """Linked sets share one band at least."""
    return "1"


def prefix(tokens: np.ndarray, percent: int, frequent: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The first tokens of a sorted set in the common order, as many as the bound needs; of each the upper 48 bits."""
    n = len(tokens)
    size = n - -(-percent * n // 100) + spare(n)
    if len(frequent):
        at = np.searchsorted(frequent, tokens)
        at[at == len(frequent)] = 0
        often = np.where(frequent[at] == tokens, counts[at], 0)
        tokens = tokens[np.argsort(often, kind="stable")]
    return tokens[:size] >> np.uint64(16)


def _six(tokens: np.ndarray) -> bytes:
    """48-bit numbers as six bytes each."""
    return np.ascontiguousarray(tokens.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6]).tobytes()


def _wide(data) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8).reshape(-1, 6)
    out = np.zeros((len(raw), 8), np.uint8)
    out[:, :6] = raw
    return out.view("<u8").reshape(-1)


def band_keys(tokens: np.ndarray, bands: int) -> np.ndarray:
    """One 48-bit key for each band: the minima of ROWS hash functions over the tokens."""
    rng = np.random.Generator(np.random.PCG64(20240229))
    odd = rng.integers(1, 1 << 63, bands * ROWS, np.uint64) * np.uint64(2) + np.uint64(1)
    add = rng.integers(0, 1 << 63, bands * ROWS, np.uint64)
    low = np.empty(bands * ROWS, np.uint64)
    for at in range(0, bands * ROWS, 8):
        h = tokens[None, :] * odd[at : at + 8, None] + add[at : at + 8, None]
        h ^= h >> np.uint64(32)
        h *= np.uint64(0xD6E8FEB86659FD93)
        low[at : at + 8] = h.min(axis=1)
    key = np.arange(bands, dtype=np.uint64)
    for i in range(ROWS):
        key = mix(key * _ODD + low[i::ROWS])
    return key >> np.uint64(16)


def bands_for(percent: int, miss: float) -> int:
    """Bands, so that a pair at the threshold shares none of them with probability ``miss`` at most."""
    return math.ceil(math.log(miss) / math.log(1 - (percent / 100) ** ROWS))


def signatures(docs: DataFrame, n: int, percent: int, exact: bool, miss: float) -> DataFrame:
    """doc_id, key, n_shingles, a 128-bit digest of the set (d1, d2) and its keys (null without shingles)."""
    often = docs.sparkSession.sparkContext.broadcast(frequent_shingles(docs, n)) if exact else None
    bands = bands_for(percent, miss)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = (lambda t: prefix(t, percent, *often.value)) if often else (lambda t: band_keys(t, bands))
        for batch in batches:
            sizes, d1, d2, keys = [], [], [], []
            for text in batch.column("text").to_pylist():
                tokens = shingle_set(text, n)
                sizes.append(len(tokens))
                d1.append(tokens.sum(dtype=np.uint64))
                d2.append(np.bitwise_xor.reduce(mix(tokens + np.uint64(1))) if len(tokens) else np.uint64(0))
                keys.append(_six(of(tokens)) if len(tokens) else None)
            longs = lambda x: pa.array(np.array(x, np.uint64).view(np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("key"), pa.array(sizes, pa.int64()), longs(d1), longs(d2), pa.array(keys, pa.binary())],
                ["doc_id", "key", "n_shingles", "d1", "d2", "keys"],
            )

    keyed = docs.select("doc_id", F.xxhash64("text").alias("key"), "text")
    return keyed.mapInArrow(run, "doc_id long, key long, n_shingles long, d1 long, d2 long, keys binary")


def shared_tokens(classes: DataFrame) -> DataFrame:
    """bucket, id and n for the keys that several classes (id, n, keys) hold.

    Keys travel packed: a message holds a batch's keys of one range, and whose they are: some ten bytes a key. One key's classes meet in one range.
    """
    total = classes.agg(F.sum(F.length("keys") / 6)).first()[0] or 0
    bits = max(3, int(total / RANGE_TOKENS).bit_length())

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            tokens = [_wide(k.as_buffer()) for k in batch.column("keys")]
            owner = np.repeat(np.arange(len(tokens), dtype=np.uint32), [len(t) for t in tokens])
            every = np.concatenate(tokens) if tokens else np.zeros(0, np.uint64)
            where = (every * _ODD) >> np.uint64(64 - bits)
            order = np.lexsort((every, where))
            every, owner, where = every[order], owner[order], where[order]
            ids, sizes = batch.column("id").to_numpy(), batch.column("n").to_numpy()
            out: list[list] = [[], [], [], []]
            cuts = np.searchsorted(where, np.arange((1 << bits) + 1, dtype=np.uint64))
            for r, (a, z) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                if a < z:
                    mine, at = np.unique(owner[a:z], return_inverse=True)
                    who = np.stack([ids[mine], sizes[mine].astype(np.int64)])
                    for column, value in zip(out, (r, _six(every[a:z]), at.astype(np.uint32).tobytes(), who.tobytes()), strict=True):
                        column.append(value)
            yield pa.RecordBatch.from_arrays(
                [pa.array(out[0], pa.int32()), *[pa.array(c, pa.binary()) for c in out[1:]]], ["range", "tokens", "owner", "who"]
            )

    def meet(key, group):
        tokens, ids, sizes = [], [], []
        for t, o, w in zip(*[group.column(c).to_pylist() for c in ("tokens", "owner", "who")], strict=True):
            who, owner = np.frombuffer(w, np.int64).reshape(2, -1), np.frombuffer(o, np.uint32)
            tokens.append(_wide(t))
            ids.append(who[0][owner])
            sizes.append(who[1][owner])
        every, ids, sizes = np.concatenate(tokens), np.concatenate(ids), np.concatenate(sizes)
        order = np.lexsort((ids, every))
        every, ids, sizes = every[order], ids[order], sizes[order]
        same = (every[1:] == every[:-1]) & (ids[1:] == ids[:-1])  # two tokens of a class that 48 bits don't tell apart
        once = np.append(True, ~same)
        every, ids, sizes = every[once], ids[once], sizes[once]
        _, back, count = np.unique(every, return_inverse=True, return_counts=True)
        many = count[back] > 1
        return pa.table({"bucket": every[many].view(np.int64), "id": ids[many], "n": pa.array(sizes[many], pa.int32())})

    sent = classes.select("id", "n", "keys").mapInArrow(send, "range int, tokens binary, owner binary, who binary")
    return sent.groupBy("range").applyInArrow(meet, "bucket long, id long, n int")


def _linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets reach the threshold."""
    left = pairs.join(sets.select(F.col("node").alias("a"), F.col("tokens").alias("ta")), "a")
    both = left.join(sets.select(F.col("node").alias("b"), F.col("tokens").alias("tb")), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = [
                _linked(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64), percent)
                for x, y in zip(batch.column("ta"), batch.column("tb"), strict=True)
            ]
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    return both.select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long")


def open_groups(queries: list[np.ndarray], members: list[np.ndarray], percent: int) -> tuple[np.ndarray, list[int]]:
    """Overlap counts of queries with members, where the members' token union lets a query in.

    The overlap of linked sets x, y is at least percent/100 of either size, so a query enters
    only if that much of it lies in the union. Returns the counts and the queries let in.
    """
    union, place = np.unique(np.concatenate(members), return_inverse=True)
    owner = np.repeat(np.arange(len(members)), [len(m) for m in members])
    order = np.argsort(place, kind="stable")
    by_token, starts = owner[order], np.searchsorted(place[order], np.arange(len(union) + 1))
    counts, inside = [], []
    for i, q in enumerate(queries):
        at = np.searchsorted(union, q)
        at[at == len(union)] = 0
        at = at[union[at] == q]
        if 100 * len(at) < percent * len(q) or not len(at):
            continue
        owners = np.concatenate([by_token[s:e] for s, e in zip(starts[at], starts[at + 1], strict=True)])
        counts.append(np.bincount(owners, minlength=len(members)))
        inside.append(i)
    return np.array(counts).reshape(-1, len(members)), inside


class _Unions:
    """Union-find over the components that a task meets."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        path = []
        while (y := self.up.get(x, x)) != x:
            path.append(x)
            x = y
        for p in path:
            self.up[p] = x
        return x

    def join(self, x: int, y: int) -> bool:
        """False if they were one already."""
        x, y = self.root(x), self.root(y)
        self.up[x] = y
        return x != y


def _opened(asked: DataFrame, percent: int) -> DataFrame:
    """Links that join different components, for rows (grp, block, side, node, comp, tokens): askers have side 0, members 1."""

    def run(key, group):
        side = group.column("side").to_numpy()
        nodes, comps = group.column("node").to_numpy(), group.column("comp").to_numpy()
        sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in group.column("tokens")]
        q, m = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        a, b = [], []
        if len(q) and len(m):
            counts, inside = open_groups([sets[i] for i in q], [sets[i] for i in m], percent)
            sizes = np.array([len(sets[i]) for i in m])
            known = _Unions()
            for row, i in zip(counts, (q[j] for j in inside), strict=True):
                ok = np.flatnonzero((100 * row >= percent * (len(sets[i]) + sizes - row)) & (comps[m] != comps[i]))
                # one link to each component is enough, and none to those that this task has joined already
                for comp, j in zip(*np.unique(comps[m][ok], return_index=True), strict=True):
                    if known.join(int(comps[i]), int(comp)):
                        a.append(nodes[i])
                        b.append(nodes[m][ok[j]])
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return asked.groupBy("grp", "block").applyInArrow(run, "a long, b long")


def components(edges: DataFrame, tag: str = "cc") -> DataFrame:
    """node and comp (smallest node reachable) for every node of an edge: stored.

    Each round takes the least label of the neighbours and then the label of that label.
    """
    both = store(
        edges.select(F.col("a").alias("node"), F.col("b").alias("other"))
        .union(edges.select(F.col("b").alias("node"), F.col("a").alias("other")))
        .distinct(),
        tag,
    )
    now = store(both.df.groupBy("node").agg(F.least(F.min("other"), F.first("node")).alias("comp")), tag)
    while True:
        labels = now.df
        near = both.df.join(labels.select(F.col("node").alias("other"), "comp"), "other").groupBy("node").agg(F.min("comp").alias("least"))
        lower = labels.join(near, "node").select("node", F.col("comp").alias("was"), F.least("comp", "least").alias("to"))
        jump = lower.join(labels.select(F.col("node").alias("to"), F.col("comp").alias("next")), "to", "left")
        after = store(
            jump.select("node", F.least("to", F.coalesce("next", "to")).alias("comp"), (F.least("to", F.coalesce("next", "to")) != F.col("was")).alias("moved")),
            tag,
        )
        now.drop()
        done = not after.df.where("moved").limit(1).count()
        now = after
        if done:
            both.drop()
            return now.df.select("node", "comp")


def jaccard_groups(docs: DataFrame, n: int, percent: int, exact: bool = False, miss: float = 1e-10) -> DataFrame:
    """Per row of docs (doc_id, text): doc_id, key (hash of the text), n_shingles, id (its class), node (the class's least doc_id), component_id."""
    docs = docs.select(F.coalesce("doc_id", F.lit(NO_ID)).alias("doc_id"), "text")
    made = signatures(docs, n, percent, exact, miss)
    need = _spare if exact else _one
    seen = materialise(made.withColumn("id", F.xxhash64("d1", "d2", "n_shingles")), "tg-sets")
    classes = store(
        seen.where("n_shingles > 0").groupBy("id").agg(F.min("doc_id").alias("node"), F.min_by("keys", "doc_id").alias("keys"), F.first("n_shingles").cast("int").alias("n")),
        "tg-class",
    )
    shared = store(shared_tokens(classes.df), "tg-shared")
    pivots = shared.df.groupBy("bucket").agg(F.min(F.struct(F.xxhash64("id").alias("o"), "id", "n")).alias("p")).select(
        "bucket", F.col("p.id").alias("b"), F.col("p.n").alias("m")
    )
    near = f"100 * least(n, m) >= {percent} * greatest(n, m) and 3 * c >= {need('least(n, m)')}"
    stars = store(
        shared.df.join(pivots, "bucket").where("id <> b").groupBy(F.col("id").alias("a"), "b", "n", "m").agg(F.count(F.lit(1)).alias("c")).where(near).select("a", "b"),
        "tg-stars",
    )
    sets = _sets_of(docs, n, classes.df, stars.df.select(F.col("a").alias("id")).union(stars.df.select("b")))
    links = store(verified(stars.df, sets.df, percent), "tg-links")
    comps = components(links.df)
    more = store(matrix_links(shared.df, comps, docs, n, classes.df, percent, need), "tg-more")
    # links between components are joined as links of their names
    named = more.df.join(comps.select(F.col("node").alias("a"), F.col("comp").alias("ca")), "a", "left").join(
        comps.select(F.col("node").alias("b"), F.col("comp").alias("cb")), "b", "left"
    )
    above = components(named.select(F.coalesce("ca", "a").alias("a"), F.coalesce("cb", "b").alias("b")).where("a <> b").distinct())
    lone = above.select("node", F.col("comp").alias("higher"))
    last = (
        comps.select("node", F.col("comp").alias("mine"))
        .union(above.join(comps, "node", "left_anti").select("node", F.col("node").alias("mine")))
        .join(lone.withColumnRenamed("node", "mine"), "mine", "left")
        .select("node", F.coalesce("higher", "mine").alias("comp"))
    )
    # a component is named after its smallest doc_id
    led = classes.df.select("id", "node").join(last.select(F.col("node").alias("id"), "comp"), "id", "left")
    least = store(led.where("comp is not null").groupBy("comp").agg(F.min("node").alias("least")), "tg-least")
    found = materialise(
        led.join(least.df, "comp", "left").select("id", "node", F.coalesce("least", "node").alias("component_id")), "tg-out"
    )
    for x in (classes, stars, shared, sets, least):
        x.drop()
    real = lambda c: F.nullif(c, F.lit(NO_ID))
    return seen.join(found, "id", "left").select(
        real(F.col("doc_id")).alias("doc_id"), "key", "n_shingles", "id", "node", real(F.coalesce("component_id", "doc_id")).alias("component_id")
    )


def _sets_of(docs: DataFrame, n: int, classes: DataFrame, ids: DataFrame):
    """Stored: node and tokens of the classes in ``ids``, made again from the text of one document each."""
    names = store(classes.select("id", "node").join(ids.distinct(), "id", "left_semi"), "tg-names")
    wanted = docs.join(names.df.select(F.col("node").alias("doc_id")).distinct(), "doc_id", "left_semi")
    return store(_sets_of_classes(wanted, n, names.df), "tg-tokens")


def _sets_of_classes(docs: DataFrame, n: int, names: DataFrame) -> DataFrame:
    """node (the class's id) and tokens, once for each class."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingle_set(t, n) for t in batch.column("text").to_pylist()]
            d1 = np.array([s.sum(dtype=np.uint64) for s in sets], np.uint64).view(np.int64)
            d2 = np.array([np.bitwise_xor.reduce(mix(s + np.uint64(1))) if len(s) else 0 for s in sets], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays(
                [pa.array(d1), pa.array(d2), pa.array([len(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())],
                ["d1", "d2", "n", "tokens"],
            )

    made = docs.select("text").mapInArrow(run, "d1 long, d2 long, n long, tokens binary")
    named = made.where("n > 0").select(F.xxhash64("d1", "d2", "n").alias("id"), "tokens")
    return named.join(names.select("id"), "id", "left_semi").select(F.col("id").alias("node"), "tokens").dropDuplicates(["node"])


def partition_groups(rows: DataFrame) -> DataFrame:
    """node, comp, n, rank, cluster and grp: each class in one group, similar ones together; rows are (bucket, its number of classes k, node, n, comp, rank)."""
    # classes of one cluster share its largest buckets: each follows its largest one, and a bucket the largest that its own classes follow
    each = rows.groupBy("node", "comp", "n", "rank").agg(F.max(F.struct("k", "bucket")).alias("first"))
    lead = store(rows.select("bucket", "node").join(each.select("node", "first"), "node").groupBy("bucket").agg(F.max("first")["bucket"].alias("lead")), "tg-lead").df
    twice = lead.join(lead.select(F.col("bucket").alias("lead"), F.col("lead").alias("top")), "lead").select("bucket", "top")
    sizes = each.groupBy("comp").agg(F.count(F.lit(1)).alias("of_comp"))
    keyed = each.withColumn("bucket", F.col("first.bucket")).join(twice, "bucket").join(sizes, "comp")
    keyed = keyed.withColumn("cluster", F.when(F.col("of_comp") > GROUP // 2, F.xxhash64("comp")).otherwise(F.xxhash64("top", F.lit(1))))
    parts = keyed.groupBy("cluster").agg(F.ceil(F.greatest(F.count(F.lit(1)) / GROUP, F.sum("n") / GROUP_TOKENS)).alias("parts"))
    dealt = keyed.join(parts, "cluster").withColumn("part", F.pmod(F.xxhash64("node"), "parts"))
    return dealt.select("node", "comp", "n", "rank", "cluster", F.xxhash64("cluster", "part").alias("grp"))


def _meet(asks: DataFrame, offered: DataFrame, on: str, tag: str) -> DataFrame:
    """asks joined with what is offered on a key; a key with many of both is dealt out: each asker meets all that is offered in one part."""
    numbers = asks.groupBy(on).agg(F.count(F.lit(1)).alias("a")).join(offered.groupBy(on).agg(F.count(F.lit(1)).alias("g")), on)
    plan = store(numbers.select(on, F.ceil(F.col("a") * F.col("g") / PAIRS).alias("salts")), tag).df
    salted = asks.join(plan, on).withColumn("salt", F.pmod(F.xxhash64("node", F.lit(2)), "salts")).drop("salts")
    copies = offered.join(plan, on).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.col("salts") - 1))).drop("salts")
    return salted.join(copies, [on, "salt"]).drop("salt")


def matrix_links(shared: DataFrame, comps: DataFrame, docs: DataFrame, n: int, classes: DataFrame, percent: int, need: Callable[[str], str]) -> DataFrame:
    """Links (a, b) between components (comps: node, comp) of the classes in buckets (shared: bucket, id, n)."""
    known = shared.select("bucket", F.col("id").alias("node"), "n").join(comps, "node", "left")
    known = known.select("bucket", "node", "n", F.coalesce("comp", "node").alias("comp"))
    # by bands, all classes of a bucket have been compared with its pivot: two classes are done with
    done = 2 if need is _one else 1
    several = known.groupBy("bucket").agg(F.min("comp").alias("x"), F.max("comp").alias("y"), F.count(F.lit(1)).alias("k")).where(f"x <> y and k > {done}").select("bucket", "k")
    weight = comps.groupBy("comp").agg(F.count(F.lit(1)).alias("weight"))
    # of two components the one with the lower rank asks
    rows = store(
        known.join(several, "bucket").join(weight, "comp", "left").select("bucket", "k", "node", "n", "comp", F.struct(F.coalesce("weight", F.lit(1)).alias("weight"), "comp").alias("rank")),
        "tg-open",
    ).df
    groups = store(partition_groups(rows), "tg-groups")
    extent = [F.max("rank").alias("top"), F.min("n").alias("n0"), F.max("n").alias("n1")]
    matrix = store(rows.join(groups.df.select("node", "cluster"), "node").groupBy("bucket", "cluster").agg(*extent), "tg-matrix")
    wide = matrix.df.groupBy("bucket").agg(F.max("top").alias("highest"))
    asks = rows.join(wide, "bucket").where("rank < highest").select("bucket", "node", "n", "comp", "rank")
    fits = f"rank < top and 100 * n >= {percent} * n0 and 100 * n1 >= {percent} * n"
    met = _meet(asks, matrix.df, "bucket", "tg-plan").where(fits)
    # a linked member has at least this many tokens, and shares that many with the asker as its own size or the asker's allows
    least = f"greatest(min(n0), ceil({percent} * n / 100))"
    bound = F.expr(f"count(1) >= least({need('n')}, {need(f'cast({least} as int)')})")
    near = store(met.groupBy("node", "comp", "n", "rank", "cluster").agg(bound.alias("enough")).where("enough").drop("enough"), "tg-near").df
    parts = groups.df.groupBy("cluster", "grp").agg(*extent)
    asked = store(_meet(near, parts, "cluster", "tg-parts").where(fits).select("node", "comp", "n", "grp"), "tg-asked")
    per = F.greatest(F.count(F.lit(1)) / GROUP, F.sum("n") / GROUP_TOKENS)
    blocks = store(asked.df.groupBy("grp").agg(F.ceil(per).alias("blocks")), "tg-blocks")
    askers = asked.df.join(blocks.df, "grp").select(
        "grp", F.pmod(F.xxhash64("node", F.lit(3)), "blocks").alias("block"), F.lit(0).alias("side"), "node", "comp"
    )
    inside = store(groups.df.join(blocks.df, "grp"), "tg-inside")
    members = inside.df.select(
        "grp", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("block"), F.lit(1).alias("side"), "node", "comp"
    )
    sets = _sets_of(docs, n, classes, asked.df.select(F.col("node").alias("id")).union(inside.df.select("node")))
    return _opened(askers.union(members).join(sets.df, "node"), percent)


def keep_one(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """The rows of docs, but of each group of near copies only its first document.

    Documents without words stay. Repeated rows of a first document are one document.
    """
    ids = F.coalesce("doc_id", F.lit(NO_ID - 1))
    found = store(jaccard_groups(docs.select(ids.alias("doc_id"), "text"), words, percent), "tg-found").df
    lone = found.where("n_shingles = 0").select("doc_id", "key", F.lit(1).alias("rows")).distinct()
    # a component's first class, then its first text: a doc_id may be repeated with other texts
    first = found.where("n_shingles > 0 and doc_id = component_id").groupBy("component_id").agg(F.min("key").alias("key"))
    led = found.where("n_shingles > 0").join(store(first, "tg-first").df, ["component_id", "key"]).where("doc_id = component_id")
    kept = store(lone.union(led.groupBy("doc_id", "key").agg(F.count(F.lit(1)).cast("int").alias("rows"))), "tg-kept").df
    keyed = docs.select(F.struct("*").alias("kept"), ids.alias("doc_id"), F.xxhash64("text").alias("key"))
    joined = keyed.join(kept, ["doc_id", "key"])
    once, more = joined.where("rows = 1"), joined.where("rows > 1").dropDuplicates(["doc_id", "key"])
    return once.unionByName(more).select("kept.*")


def op8_token_group_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = jaccard_groups(table(spark, sf_dir, "documents"), 4, 85)
    return found.select("doc_id", "n_shingles", "component_id")
