"""PII: information-theoretic sanitisation.

Protected entities are found by pattern (email, ip, card, phone). The corpus then tells how
strongly other terms reveal them. All counts are of distinct texts, so copies of a document prove nothing.
For a term t and one entity value v, t discloses v when the pointwise mutual information log2(P(v|t) / P(v))
reaches ``tau`` of v's information content -log2 P(v), and their meeting is no chance: the bound exp(-n KL(c/n, h/N))
on the probability that c of the n texts with t hold v (h of all N do), times the number of (term, value)
pairs that could meet, stays under the normal tail beyond ``z``. A term discloses a whole kind K in the same way,
with P(K|t) taken at its lower confidence bound. Documents that hold v, or an entity of kind K, get spans
of kind ``term`` for the terms disclosing it: numbers are generalised, other terms removed.
Near copies are different texts: what they share beside an address does disclose it.

Native: patterns run inside the row as built-in expressions; all patterns are linear in the text
(possessive loops, starts anchored at the edge of a run). Documents are gated by a character
search first. Term counts are combined before the shuffle. Only documents with an entity have their words located.

Defined results: null text counts as empty and has no spans (the sanitiser leaves it null);
repeated rows are treated alike, each on its own; an empty table gives an empty result.
Other columns pass through the sanitiser untouched (n_chars, if there, follows the text).
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACE_CLASS, let, materialise, store, table

KINDS = ("email", "ip", "card", "phone")
#: Linear forms of the contract's patterns. A match can only begin where its run of characters begins
#: or where the match before it ended (\G); a loop that ends a pattern never gives back.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
OCTETS = r"^0*(25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(\.0*(25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])){3}$"
SPAN = "array<struct<kind:int,start:int,end:int,value:string>>"


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    def add(total: Column, i: Column) -> Column:
        d = F.substring(F.reverse(digits), i + 1, F.lit(1)).cast("int")
        twice = F.when(d > 4, 2 * d - 9).otherwise(2 * d)
        return total + F.when(i % 2 == 1, twice).otherwise(d)

    return F.aggregate(F.sequence(F.lit(0), F.length(digits) - 1), F.lit(0), add) % 10 == 0


def _valid(kind: str, value: Column) -> Column:
    if kind == "ip":
        return value.rlike(OCTETS)
    if kind == "card":
        return let(_digits(value), lambda d: F.when(F.length(d).between(13, 19), _luhn(d)).otherwise(F.lit(False)))
    if kind == "phone":
        return F.length(_digits(value)).between(9, 15)
    return F.lit(True)


def _gate(kind: str, text: Column) -> Column:
    if kind == "email":
        return F.contains(text, F.lit("@"))
    if kind == "phone":
        return F.contains(text, F.lit("+"))
    return text.rlike(r"[0-9]\.[0-9]" if kind == "ip" else r"[0-9][\x20-]?[0-9]")


def _located(pieces: Column, matches: Column, kind: Column) -> Column:
    """Spans of the matches, from what stands between them: lengths add up to code points."""
    pairs = F.zip_with(
        F.slice(pieces, F.lit(1), F.size(matches)),
        matches,
        lambda p, m: F.struct(F.length(p).alias("gap"), F.length(m).alias("len"), m.alias("m")),
    )
    empty = F.struct(F.lit(0).alias("at"), F.array().cast(SPAN).alias("out"))

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + x["gap"]
        span = F.struct(kind.alias("kind"), start.alias("start"), (start + x["len"]).alias("end"), x["m"].alias("value"))
        return F.struct((start + x["len"]).alias("at"), F.concat(acc["out"], F.array(span)).alias("out"))

    return F.aggregate(pairs, empty, step, lambda acc: acc["out"])


def _spans(kind: str, text: Column) -> Column:
    pattern = PATTERNS[kind]
    both = F.struct(
        F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("m"), F.split(text, pattern, -1).alias("s")
    )
    found = let(both, lambda x: _located(x["s"], x["m"], F.lit(KINDS.index(kind))))
    checked = found if kind == "email" else F.filter(found, lambda x: _valid(kind, x["value"]))
    return F.when(_gate(kind, text), checked).otherwise(F.array().cast(SPAN))


def base_spans(text: Column) -> Column:
    """All entities of a text, by kind and then start."""
    t = F.coalesce(text, F.lit(""))
    return F.concat(*[_spans(k, t) for k in KINDS])


def _term_places(text: Column, term: Column) -> Column:
    """Spans of the places where ``term`` stands as a word: lengths between them add up."""
    quoted = F.concat(F.lit("\\Q"), F.replace(term, F.lit("\\E"), F.lit("\\E\\\\E\\Q")), F.lit("\\E"))
    pattern = F.concat(F.lit(r"(?<![^\x20\x09-\x0D])"), quoted, F.lit(r"(?![^\x20\x09-\x0D])"))
    return let(
        F.split(text, pattern, -1),
        lambda s: _located(s, F.array_repeat(term, F.size(s) - 1), F.lit(len(KINDS))),
    )


def find_entities(docs: DataFrame, carry: list[str]) -> DataFrame:
    """Stored: ``carry``, __row, __h0 and __h1 (of the text), __base (spans) and __text, the latter only where there are spans."""
    spans = docs.select(*carry, F.col("text").alias("__t"), base_spans(F.col("text")).alias("__base"))
    return materialise(
        spans.select(
            *carry,
            F.monotonically_increasing_id().alias("__row"),
            *[h.alias(f"__h{i}") for i, h in enumerate(_hashes("__t"))],
            "__base",
            F.when(F.size("__base") > 0, F.col("__t")).alias("__text"),
        ),
        "pii-found",
    )


def _hashes(name: str) -> list[Column]:
    text = F.coalesce(F.col(name), F.lit(""))
    return [F.xxhash64(text), F.xxhash64(text, F.lit(1))]


def _marks() -> Column:
    """What a text protects: each of its values, and each kind as a whole (kind + len(KINDS), 0)."""
    values = F.transform("__base", lambda s: F.struct(s["kind"].alias("kind"), F.xxhash64(s["value"]).alias("v")))
    kinds = F.transform("__base", lambda s: F.struct((s["kind"] + len(KINDS)).alias("kind"), F.lit(0).cast("long").alias("v")))
    return F.array_distinct(F.concat(values, kinds))


def _terms(name: str) -> Column:
    return F.array_distinct(F.filter(F.split(F.coalesce(F.col(name), F.lit("")), SPACE_CLASS), lambda w: w != ""))


def disclosing_terms(docs: DataFrame, found: DataFrame, tau: float, z: float) -> DataFrame:
    """term, kind and v (see ``_marks``) of what each disclosing term reveals: stored, with the estimates."""
    hits = found.where(F.size("__base") > 0).select("__h0", "__h1", "__base", "__text")
    once = store(hits.dropDuplicates(["__h0", "__h1"]).select(_marks().alias("marks"), _terms("__text").alias("terms")), "pii-once")
    texts = docs.select("text", *[h.alias(f"h{i}") for i, h in enumerate(_hashes("text"))]).dropDuplicates(["h0", "h1"])
    holds = store(texts.select(F.explode(_terms("text")).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("n")), "pii-holds")
    marks = store(once.df.select(F.explode("marks").alias("m")).groupBy("m.kind", "m.v").agg(F.count(F.lit(1)).alias("h")), "pii-marks")
    total = found.select("__h0", "__h1").distinct().count()
    tests = holds.df.count() * marks.df.where(F.col("kind") < len(KINDS)).count()
    need = math.log(max(tests, 1) / (math.erfc(z / math.sqrt(2)) / 2))
    # the least a pair needs, were all texts of the term and of the mark the same ones: no other can pass below
    rare = max(total, 2) ** (tau - 1)
    c, h, n, every = F.col("c").cast("double"), F.col("h").cast("double"), F.col("n").cast("double"), F.lit(float(total))
    whole = F.col("kind") >= len(KINDS)
    hope = F.when(whole, c >= z * z * rare / (1 - rare) - 1e-6).otherwise(c * F.log(every / c) >= need - 1e-6)
    pairs = once.df.select(F.explode("terms").alias("term"), "marks").select("term", F.explode("marks").alias("m"))
    candidates = store(
        pairs.groupBy("term", "m.kind", "m.v").agg(F.count(F.lit(1)).alias("c")).where(hope).withColumn("salt", F.pmod(F.xxhash64("term"), F.lit(16))),
        "pii-terms",
    )
    salted = marks.df.where((F.col("h") > 1) | F.lit(math.log(max(total, 1)) >= need)).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(15).cast("long"))))
    q, p0 = c / n, h / every
    low = (q + z * z / (2 * n) - z * F.sqrt(q * (1 - q) / n + z * z / (4 * n * n))) / (1 + z * z / n)
    chance = n * (q * F.log(q / p0) + F.when(q < 1, (1 - q) * F.log((1 - q) / (1 - p0))).otherwise(0.0))
    scored = (
        candidates.df.join(salted, ["kind", "v", "salt"])
        .join(holds.df, "term")
        .withColumn("content", -F.log2(p0))
        .withColumn("pmi", F.log2(F.greatest(F.when(whole, low).otherwise(q), F.lit(1e-12))) + F.col("content"))
        .where((F.col("content") > 0) & (F.col("pmi") >= tau * F.col("content")) & (whole | (chance >= need)))
    )
    out = store(scored.select("term", "kind", "v", "n", "c", "pmi", "content"), "pii-disclosing")
    for x in (once, holds, marks, candidates):
        x.drop()
    return out.df


def term_spans(found: DataFrame, terms: DataFrame) -> DataFrame:
    """__row and __more: the spans of disclosing terms, outside the entities themselves.

    Words are matched without the text; only documents that hold a disclosing term are read again.
    """
    hits = found.where(F.size("__base") > 0)
    words = hits.select("__row", _marks().alias("marks"), F.explode(_terms("__text")).alias("term"))
    reveals = terms.groupBy("term").agg(F.collect_set(F.struct("kind", "v")).alias("what"))
    mine = (
        words.join(reveals, "term")
        .where(F.arrays_overlap("marks", "what"))
        .groupBy("__row")
        .agg(F.array_sort(F.collect_set("term")).alias("terms"))
    )
    located = hits.join(mine, "__row").withColumn(
        "all", F.flatten(F.transform("terms", lambda t: _term_places(F.col("__text"), t)))
    )
    free = F.filter(
        "all", lambda w: ~F.exists("__base", lambda s: (s["start"] < w["end"]) & (s["end"] > w["start"]))
    )
    return located.select("__row", F.array_sort(free).alias("__more"))


def protected(
    docs: DataFrame, carry: list[str], tau: float = 0.9, z: float = 4.0
) -> DataFrame:
    """``carry`` plus __base and __more spans for each row."""
    found = find_entities(docs, carry)
    terms = disclosing_terms(docs, found, tau, z)
    return found.drop("__h0", "__h1").join(term_spans(found, terms), "__row", "left").withColumn(
        "__more", F.coalesce("__more", F.array().cast(SPAN))
    )


def _replaced(text: Column, spans: Column) -> Column:
    """The text with each span replaced; of overlapping spans the earliest, then longest, wins."""
    ordered = F.array_sort(
        F.transform(spans, lambda s: F.struct(s["start"].alias("start"), (-s["end"]).alias("far"), s["kind"].alias("kind"), s["value"].alias("value")))
    )
    tags = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])

    def step(acc: Column, s: Column) -> Column:
        end = -s["far"]
        tag = F.coalesce(F.get(tags, s["kind"]), F.when(s["value"].rlike("[0-9]"), "[NUMBER]").otherwise("[TERM]"))
        fresh = s["start"] >= acc["at"]
        piece = F.concat(acc["out"], F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), tag)
        return F.struct(
            F.greatest(acc["at"], end).alias("at"), F.when(fresh, piece).otherwise(acc["out"]).alias("out")
        )

    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    return F.aggregate(
        ordered, start, step, lambda a: F.concat(a["out"], F.substring(text, a["at"] + 1, F.length(text)))
    )


def sanitise(docs: DataFrame, **options) -> DataFrame:
    """The same rows and columns with entities and disclosing terms replaced."""
    # the row travels as one value: no column of it can clash with ours
    rows = protected(docs.select(F.struct("*").alias("whole"), "text"), ["whole"], **options)
    old = F.col("whole.text")
    new = let(F.concat("__base", "__more"), lambda s: F.when(F.size(s) > 0, _replaced(old, s)).otherwise(old))
    size = F.coalesce(F.length(new).cast(docs.schema["n_chars"].dataType), F.col("whole.n_chars")) if "n_chars" in docs.columns else None
    fresh = {"text": new, "n_chars": size}
    return rows.select(*[fresh.get(c, F.col(f"whole.`{c}`")).alias(c) for c in docs.columns])


def _written(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in (*KINDS, "term")])
    return F.array_join(
        F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ","
    )


def _count_of(kind: int):
    """A step that counts one kind (its number bound here: a second lambda parameter would mean the index)."""
    return lambda n, k: n + F.when(k == kind, 1).otherwise(0)


def op7_pii_disclosure(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = protected(table(spark, sf_dir, "documents").select("doc_id", "text"), ["doc_id"])
    counts = [
        F.aggregate("__base.kind", F.lit(0).cast("long"), _count_of(k)).alias(f"n_{name}")
        for k, name in enumerate(KINDS)
    ]
    return rows.select(
        "doc_id",
        *counts,
        F.sha2(_written(F.col("__base")), 256).alias("base_sha256"),
        _written(F.concat("__base", "__more")).alias("spans"),
    )
