"""Quality rules: robust multivariate outliers by minimum covariance determinant.

Each document becomes a vector of five transformed statistics. For every
(language, source) group a location and a scatter are estimated from the
fraction ``support`` of the documents with the smallest Mahalanobis distances,
by concentration steps from a start at the medians; then reweighted once. Documents
far from their group's estimate are rejected.

Native: one scan computes the statistics (array functions inside the row, no shuffle of
words), everything after works on a narrow table of numbers. A concentration step is one
grouped sum and one histogram of distances, both combined before the shuffle, so a group
with a third of all rows costs no more than any other.

Defined results: null text counts as empty text (no words, base_failed). Null lang or
source form a group of their own. Groups below ``min_group`` documents use their
language's pooled estimate, and small languages the pooled estimate of all. Repeated rows are
judged alike. An empty table gives an empty result. Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACES, let, store, table, words_of

FEATURES = ("f_len", "f_word", "f_sym", "f_dup", "f_rep")
#: Least variance of each transformed statistic: below it, differences say nothing about quality.
FLOORS = (1.0, 0.01, 0.09, 0.04, 0.04)
#: Files of a table with one row per group.
FILES = 8
#: Upper quantiles of the chi-square law with five degrees of freedom, fixed values: 0.5 and 0.975.
CHI_MEDIAN, CHI_REWEIGHT = 4.351, 12.833


def _repeated_words(words: Column) -> Column:
    """Number of word positions inside three-word windows that occur at least twice."""

    def marked(w: Column) -> Column:
        windows = F.transform(
            F.when(F.size(w) >= 3, F.sequence(F.lit(0), F.size(w) - 3)).otherwise(F.array().cast("array<int>")),
            lambda i: F.struct(F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)).alias("h"), i.alias("p")),
        )
        return let(F.array_sort(windows), twice)

    def twice(s: Column) -> Column:
        same = F.filter(
            s,
            lambda x, i: F.coalesce(F.get(s, i - 1)["h"] == x["h"], F.lit(False))
            | F.coalesce(F.get(s, i + 1)["h"] == x["h"], F.lit(False)),
        )
        return F.size(F.array_distinct(F.flatten(F.transform(same, lambda x: F.array(x["p"], x["p"] + 1, x["p"] + 2)))))

    return let(words, marked)


def text_statistics(docs: DataFrame, keep: tuple[str, ...] = ("doc_id", "lang", "source")) -> DataFrame:
    """``keep`` and the exact counts that the rules need."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: F.translate(x, SPACES, "") != "")
    words = words_of(F.col("text"))
    counted = let(words, lambda w: F.struct(F.size(w).alias("n"), _repeated_words(w).alias("rep")))
    listed = let(lines, lambda x: F.struct(F.size(x).alias("n"), F.size(F.array_distinct(x)).alias("d")))
    return docs.select(
        *keep,
        F.length(F.translate(text, SPACES, "")).cast("long").alias("word_chars"),
        F.length(F.regexp_replace(text, "[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        counted.alias("__w"),
        listed.alias("__l"),
    ).select(
        *keep,
        F.col("__w.n").cast("long").alias("n_words"),
        "word_chars",
        "n_symbols",
        (F.col("__l.n") - F.col("__l.d")).cast("long").alias("n_dup_lines"),
        F.col("__w.rep").cast("long").alias("n_repeat_words"),
        F.col("__l.n").cast("long").alias("n_lines"),
    )


def _vector(stats: DataFrame) -> DataFrame:
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    return stats.withColumns(
        {
            "f_len": F.log1p(F.col("n_words").cast("double")),
            "f_word": F.log1p(F.col("word_chars") / n),
            "f_sym": F.log1p(100.0 * F.col("n_symbols") / F.greatest(F.col("word_chars"), F.lit(1))),
            "f_dup": F.sqrt(F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1))),
            "f_rep": F.sqrt(F.col("n_repeat_words") / n),
        }
    )


def _moments(rows: DataFrame) -> DataFrame:
    """Per group: count, means and the inverse Cholesky factor of the floored covariance."""
    d = len(FEATURES)
    sums = [F.count(F.lit(1)).cast("double").alias("m")]
    sums += [F.sum(f).alias(f"s{i}") for i, f in enumerate(FEATURES)]
    sums += [F.sum(F.col(FEATURES[i]) * F.col(FEATURES[j])).alias(f"q{i}{j}") for i in range(d) for j in range(i + 1)]
    out = rows.groupBy("grp").agg(*sums)
    out = out.withColumns({f"u{i}": F.col(f"s{i}") / F.col("m") for i in range(d)})
    cov = {
        f"c{i}{j}": F.col(f"q{i}{j}") / F.col("m") - F.col(f"u{i}") * F.col(f"u{j}") + (FLOORS[i] if i == j else 0.0)
        for i in range(d)
        for j in range(i + 1)
    }
    return _inverse_factor(out.withColumns(cov)).select(
        "grp", "m", *[f"u{i}" for i in range(d)], *[f"v{i}{j}" for i in range(d) for j in range(i + 1)]
    )


def _inverse_factor(df: DataFrame) -> DataFrame:
    """Adds v = L^-1 for c = L L', entry by entry, as plain columns."""
    d = len(FEATURES)
    for j in range(d):
        for i in range(j, d):
            rest = F.col(f"c{i}{j}")
            for k in range(j):
                rest = rest - F.col(f"l{i}{k}") * F.col(f"l{j}{k}")
            df = df.withColumn(f"l{i}{j}", F.sqrt(F.greatest(rest, F.lit(1e-9))) if i == j else rest / F.col(f"l{j}{j}"))
    for j in range(d):
        for i in range(j, d):
            if i == j:
                value = 1.0 / F.col(f"l{i}{i}")
            else:
                value = F.lit(0.0)
                for k in range(j, i):
                    value = value - F.col(f"l{i}{k}") * F.col(f"v{k}{j}")
                value = value / F.col(f"l{i}{i}")
            df = df.withColumn(f"v{i}{j}", value)
    return df


def _distance() -> Column:
    total = None
    for i in range(len(FEATURES)):
        part = F.col(f"v{i}0") * (F.col(FEATURES[0]) - F.col("u0"))
        for j in range(1, i + 1):
            part = part + F.col(f"v{i}{j}") * (F.col(FEATURES[j]) - F.col(f"u{j}"))
        total = part * part if total is None else total + part * part
    return total


def _cut(rows: DataFrame, share: float, name: str) -> DataFrame:
    """Per group the distance below which ``share`` of its rows lie, from a histogram with fixed bins."""
    from pyspark.sql import Window

    hist = rows.groupBy("grp", F.floor(F.log2(F.col("d2") + 1e-6) * 16).alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    up = Window.partitionBy("grp").orderBy("bin")
    whole = Window.partitionBy("grp")
    run = hist.select("grp", "bin", F.sum("n").over(up).alias("c"), F.sum("n").over(whole).alias("t"))
    edge = F.min(F.when(F.col("c") >= share * F.col("t"), F.col("bin")))
    # stored, so that its size is known where it meets the rows: few groups are broadcast, many are not
    return store(run.groupBy("grp").agg(F.pow(F.lit(2.0), (edge + 1) / 16.0).alias(name)), "mcd-cut", FILES).df


def estimate(vectors: DataFrame, support: float = 0.75, steps: int = 4) -> DataFrame:
    """MCD estimate per ``grp`` of a table with FEATURES: u (location), v (inverse factor), scale."""
    start = vectors.groupBy("grp").agg(
        *[F.percentile_approx(f, [0.25, 0.5, 0.75], 1000).alias(f"p{i}") for i, f in enumerate(FEATURES)]
    )
    fit = start.select(
        "grp",
        *[F.col(f"p{i}")[1].alias(f"u{i}") for i in range(len(FEATURES))],
        *[
            (
                1.0 / F.sqrt(F.pow((F.col(f"p{i}")[2] - F.col(f"p{i}")[0]) / 1.349, 2) + FLOORS[i])
                if i == j
                else F.lit(0.0)
            ).alias(f"v{i}{j}")
            for i in range(len(FEATURES))
            for j in range(i + 1)
        ],
    )
    held = store(fit, "mcd-start", FILES)  # one row for each group
    for step in range(steps + 1):
        rows = vectors.join(held.df, "grp").withColumn("d2", _distance()).select("grp", "d2", *FEATURES)
        share, name = (support, "edge") if step < steps else (0.5, "median")
        cuts = _cut(rows, share, name)
        limit = F.col("edge") if step < steps else F.col("median") * (CHI_REWEIGHT / CHI_MEDIAN)
        nearest = rows.join(cuts, "grp").where(F.col("d2") <= limit)
        after = store(_moments(nearest), "mcd-step", FILES)
        held.drop()
        held = after
    final = vectors.join(held.df, "grp").withColumn("d2", _distance()).select("grp", "d2")
    scale = _cut(final, 0.5, "median").select("grp", (F.col("median") / CHI_MEDIAN).alias("scale"))
    out = store(held.df.join(scale, "grp"), "mcd-fit", FILES)
    held.drop()
    return out.df


def score_quality(
    docs: DataFrame,
    support: float = 0.75,
    steps: int = 4,
    cutoff: float = 160.0,
    min_group: int = 50,
    carry: tuple[str, ...] = ("doc_id",),
) -> DataFrame:
    """One row per input row: ``carry``, the counts, the base rules' verdict, the robust distance and ``kept``.

    ``cutoff`` bounds the squared Mahalanobis distance, scaled so that a group's median is that of a
    chi-square law. The distance is null where there is no estimate.
    """
    stats = store(text_statistics(docs, (*carry, "lang", "source")), "mcd-stats").df
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    rows = _vector(stats).withColumn("base_failed", failed)
    lang, source = F.coalesce(F.col("lang"), F.lit("\x00")), F.coalesce(F.col("source"), F.lit("\x00"))
    rows = rows.withColumns({"g2": F.concat_ws("\x01", lang, source), "g1": lang})
    sizes = rows.groupBy("g1", "g2").agg(F.count(F.lit(1)).alias("n2"))
    langs = sizes.groupBy("g1").agg(F.sum("n2").alias("n1"))
    named = sizes.join(langs, "g1").select(
        "g2",
        F.when(F.col("n2") >= min_group, F.col("g2"))
        .when(F.col("n1") >= min_group, F.concat(F.lit("\x02"), F.col("g1")))
        .otherwise(F.lit("\x03"))
        .alias("grp"),
    )
    keys = store(named, "mcd-keys", FILES).df
    rows = rows.join(keys, "g2")
    pooled = rows.select(
        F.explode(
            F.array_distinct(F.array(F.col("grp"), F.concat(F.lit("\x02"), F.col("g1")), F.lit("\x03")))
        ).alias("grp"),
        *FEATURES,
    ).join(store(keys.select("grp").distinct(), "mcd-groups", FILES).df, "grp", "left_semi")
    fit = estimate(pooled, support, steps)
    judged = rows.join(fit, "grp", "left").withColumn("distance", _distance() / F.greatest(F.col("scale"), F.lit(1e-3)))
    return judged.select(
        *carry,
        "n_words",
        "word_chars",
        "n_symbols",
        "n_dup_lines",
        "n_repeat_words",
        "base_failed",
        (~F.col("base_failed") & (F.coalesce(F.col("distance"), F.lit(0.0)) <= cutoff)).alias("kept"),
        "distance",
    )


def keep_quality(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs that the rules keep. Rows equal in id, text, language and source are judged alike."""
    # the row travels as one value: no column of it can clash with ours
    keyed = docs.select(
        F.struct("*").alias("whole"), F.coalesce("doc_id", F.lit(-1)).alias("id"), F.xxhash64("text", "lang", "source").alias("key"), "text", "lang", "source"
    )
    bad = score_quality(keyed.drop("whole"), carry=("id", "key"), **options).where("not kept").select("id", "key").distinct()
    return keyed.select("whole", "id", "key").join(store(bad, "mcd-bad").df, ["id", "key"], "left_anti").select("whole.*")


def op1_quality_mcd(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_quality(table(spark, sf_dir, "documents"))
