"""Sharding: balanced label propagation.

Documents are linked through a shared key (by default: equal texts). Every document starts
in a shard given by its identifier; then, in rounds, the documents of a link group that sit in
one shard move together to the shard that holds most of their neighbours, as far as
that shard has room. A last step makes the counts exact (law ``rows``: at most one apart),
moving unlinked documents before linked ones, and numbers the rows of each shard.

Native: links are never expanded into pairs. A group and its start shard form a unit with
a row count, so a group with a third of all rows is at most ``shards`` units; each round is a join and
grouped sums over units. Ranks come from bounded buckets (``gapless_rank``), so no task holds a shard.
Only ``shards`` counts reach the driver.

Defined results: null text counts as empty (size 8, crc 0) and links with other null or empty texts;
repeated rows are separate rows with their own slots; an empty table gives an empty result.
Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import gapless_rank, materialise, store, table

#: Rank buckets: linked groups keep together inside a bucket, sub-buckets spread a hot group.
GROUP_BUCKETS, SUB_BUCKETS = 64, 16


def _unit_hash(*cols: Column) -> Column:
    """Even in [0, 1), the same for equal inputs."""
    return F.pmod(F.xxhash64(*cols), F.lit(1 << 30)) / float(1 << 30)


def propagate(units: DataFrame, shards: int, total: Column, rounds: int, slack: float) -> DataFrame:
    """Units (grp, home, cnt, label) -> the same with the labels after ``rounds`` rounds of moves.

    ``loads`` of the unlinked documents are given as units with a null ``grp``.
    """
    now = store(units, "lp-units")
    for step in range(rounds):
        u = now.df
        seen = u.where("grp is not null").groupBy("grp", "label").agg(F.sum("cnt").alias("near"))
        best = seen.groupBy("grp").agg(
            F.max(F.struct("near", F.xxhash64("grp", "label").alias("tie"), "label")).alias("b"), F.sum("near").alias("members")
        ).select("grp", F.col("b.label").alias("want"), "members")
        wish = u.join(best, "grp", "left").withColumn("want", F.coalesce("want", "label"))
        moves = wish.where("want <> label")
        # unlinked documents make room in the last step: only linked ones fill a shard here
        load = u.where("grp is not null").groupBy(F.col("label").alias("s")).agg(F.sum("cnt").alias("load"))
        out = moves.groupBy(F.col("label").alias("s")).agg(F.sum("cnt").alias("leaving"))
        come = moves.groupBy(F.col("want").alias("s")).agg(F.sum("cnt").alias("coming"))
        room = (
            come.join(load, "s", "left")
            .join(out, "s", "left")
            .join(total, F.lit(True))
            .select(
                F.col("s").alias("want"),
                (F.col("total") / shards).alias("fair"),
                (
                    (F.col("total") * (1.0 + slack) / shards - F.coalesce("load", F.lit(0)) + F.coalesce("leaving", F.lit(0)))
                    / F.col("coming")
                ).alias("share"),
            )
        )
        # a group moves as a whole, unless it could not fit any shard
        draw = F.when(F.col("members") > F.col("fair"), _unit_hash("grp", "home", F.lit(step))).otherwise(_unit_hash("grp", F.lit(step)))
        after = wish.join(room, "want", "left").select(
            "grp",
            "home",
            "cnt",
            F.when(
                (F.col("want") != F.col("label")) & (draw < F.coalesce("share", F.lit(0.0))),
                F.col("want"),
            )
            .otherwise(F.col("label"))
            .alias("label"),
        )
        held = store(after, "lp-units")
        now.drop()
        now = held
    return now.df


def balanced_shards(
    rows: DataFrame, group: Column, shards: int, rounds: int = 4, slack: float = 0.02
) -> DataFrame:
    """``rows`` (with doc_id) plus ``shard`` and ``slot``; counts of shards are at most one apart."""
    home = F.pmod(F.xxhash64(F.col("doc_id"), F.lit(0)), F.lit(shards)).cast("int")
    base = materialise(rows.withColumns({"grp": group, "home": home}), "lp-rows")
    cells = base.groupBy("grp", "home").agg(F.count(F.lit(1)).alias("cnt"))
    linked = cells.groupBy("grp").agg(F.sum("cnt").alias("members")).where("members > 1").select("grp")
    linked = store(linked, "lp-linked")
    tied = cells.join(linked.df, "grp", "left_semi")
    loose = (
        cells.join(linked.df, "grp", "left_anti")
        .groupBy("home")
        .agg(F.sum("cnt").alias("cnt"))
        .select(F.lit(None).cast("bigint").alias("grp"), "home", "cnt")
    )
    units = tied.unionByName(loose).withColumn("label", F.col("home"))
    # one row; it lands beside at most ``shards`` rows
    total = F.broadcast(base.groupBy().agg(F.count(F.lit(1)).alias("total")))
    placed = propagate(units, shards, total, rounds, slack).where("grp is not null")
    lab = base.join(placed.select("grp", "home", "label"), ["grp", "home"], "left").select(
        *rows.columns,
        "grp",
        F.col("label").isNotNull().alias("tied"),
        F.coalesce("label", "home").alias("label"),
    )
    bucket = F.concat_ws(
        "/",
        F.when(F.col("tied"), "a").otherwise("b"),
        F.lpad(F.pmod(F.xxhash64("grp", F.lit(1)), F.lit(GROUP_BUCKETS)).cast("string"), 3, "0"),
        F.lpad(F.pmod(F.xxhash64("doc_id", F.lit(2)), F.lit(SUB_BUCKETS)).cast("string"), 3, "0"),
    )
    ranked = store(gapless_rank(lab, ["label"], bucket, ["grp", "doc_id"], "idx"), "lp-ranked")
    have = {r["label"]: r["n"] for r in ranked.df.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    linked.drop()
    return _even(ranked.df, have, shards).select(*rows.columns, "shard", "slot", F.col("tied").alias("linked"))


def _even(ranked: DataFrame, have: dict[int, int], shards: int) -> DataFrame:
    """Rows beyond a shard's share fill the shards below theirs, in order; ``have``: rows of each shard."""
    n = sum(have.values())
    share = [n // shards + (s < n % shards) for s in range(shards)]
    over, gaps, first, a, b = [], [], [], 0, 0
    for s in range(shards):
        over.append(a)
        a += max(0, have.get(s, 0) - share[s])
        first.append(b)
        b += max(0, share[s] - have.get(s, 0))
        gaps.append(b)
    longs = lambda xs: F.array(*[F.lit(x).cast("bigint") for x in xs])
    quota = F.get(longs(share), F.col("label"))
    spare = F.get(longs(over), F.col("label")) + F.col("idx") - quota
    stays = F.col("idx") < quota
    moved = ranked.withColumn("__j", F.when(~stays, spare))
    target = F.size(F.filter(longs(gaps), lambda g: g <= F.col("__j")))
    full = longs([have.get(s, 0) for s in range(shards)])
    return moved.withColumn("shard", F.when(F.col("__j").isNull(), F.col("label")).otherwise(target).cast("int")).withColumn(
        "slot",
        F.when(F.col("__j").isNull(), F.col("idx")).otherwise(
            F.get(full, F.col("shard")) + F.col("__j") - F.get(longs(first), F.col("shard"))
        ),
    )


def op2_balanced_label_propagation(spark: SparkSession, sf_dir: str) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = table(spark, sf_dir, "documents").select(
        "doc_id",
        (F.octet_length(text) + 8).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.xxhash64(text, F.crc32(text), F.length(text)).alias("same"),
    )
    out = balanced_shards(rows, F.col("same"), 24)
    return out.select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("rows").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
        "linked",
    )
