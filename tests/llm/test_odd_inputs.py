"""Every operator and stage takes nulls, empty and long texts, ties, repeats, empty tables and clashing columns."""

from __future__ import annotations

import public_tokenizers
import pytest
from pyspark.sql import functions as F

from tracegraph.llm import decontamination, deleted_interpolation, license_rules, packing_nnls, pii_disclosure, quality_mcd, shard_propagation, token_groups
from tracegraph.llm.common import words_of

TOKENIZER = public_tokenizers.path("byte_bpe_50k.json")


def _bench(spark):
    return spark.createDataFrame([(1, "w1 w2 w3 w4 w5 w6 w7 w8"), (2, None), (None, "a b c d e"), (3, "")], "item_id long, text string")


RUNS = {
    "quality": lambda d: quality_mcd.score_quality(d),
    "licenses": lambda d: license_rules.scan_licenses(d),
    "pii": lambda d: pii_disclosure.protected(d, ["doc_id"]),
    "lm": lambda d: deleted_interpolation.score_documents(d),
    "shards": lambda d: shard_propagation.balanced_shards(d.selectExpr("doc_id", "xxhash64(text) as h"), F.col("h"), 5),
    "groups": lambda d: token_groups.jaccard_groups(d, 5, 80),
}


@pytest.mark.parametrize("name", sorted(RUNS))
def test_one_row_for_each_row(odd_docs, name):
    n = odd_docs.count()
    assert RUNS[name](odd_docs).count() == n
    assert RUNS[name](odd_docs.limit(0)).count() == 0


def test_packing(odd_docs):
    rows = packing_nnls.pack(odd_docs, TOKENIZER).collect()
    assert sum(r["length"] for r in rows if r["start"] + r["length"] == r["doc_tokens"]) > 0
    assert len([r for r in rows if r["start"] == 0]) == odd_docs.count()
    assert packing_nnls.pack(odd_docs.limit(0), TOKENIZER).count() == 0


def test_stages_keep_the_columns(spark, odd_docs):
    stages = [
        lambda d: quality_mcd.keep_quality(d),
        lambda d: token_groups.keep_one(d),
        lambda d: decontamination.clean(d, _bench(spark)),
        lambda d: pii_disclosure.sanitise(d),
    ]
    for stage in stages:
        out = stage(odd_docs)
        assert out.columns == odd_docs.columns
        assert 0 < out.count() <= odd_docs.count()
        assert stage(odd_docs.limit(0)).count() == 0
    assert decontamination.clean(odd_docs, _bench(spark).limit(0)).count() == odd_docs.count()


NAMES = ["rows", "row", "__id", "__key", "__row", "__base", "__more", "__text", "whole", "kept", "key", "id", "grp", "h0", "node", "tokens"]


def test_stages_take_columns_of_any_name(spark, odd_docs):
    clashing = odd_docs.drop("key", "id").select("*", *[F.lit(i).alias(n) for i, n in enumerate(NAMES)])
    for stage in (quality_mcd.keep_quality, token_groups.keep_one, lambda d: decontamination.clean(d, _bench(spark)), pii_disclosure.sanitise):
        out = stage(clashing)
        assert out.columns == clashing.columns
        assert {tuple(r) for r in out.select(*NAMES).collect()} == {tuple(range(len(NAMES)))}


def test_null_ids_of_the_join(spark):
    text = " ".join(f"w{i}" for i in range(30))
    df = spark.createDataFrame([(None, text), (None, text + " x"), (7, "other words here"), (None, "a b c d e f"), (None, None), (3, text)], "doc_id long, text string")
    rows = sorted((r["doc_id"] is None, r["doc_id"] or 0, r["n_shingles"], r["component_id"]) for r in token_groups.jaccard_groups(df, 4, 85).collect())
    assert (False, 3, 27, 3) in rows and (True, 0, 27, 3) in rows and (True, 0, 28, 3) in rows
    assert (True, 0, 3, None) in rows and (True, 0, 0, None) in rows


def test_short_benchmark_items_match_whole(spark):
    docs = spark.createDataFrame([(1, "say hello world again"), (2, "hello there world"), (3, "nothing")], "doc_id long, text string")
    bench = spark.createDataFrame([(5, "Hello, world!"), (6, "")], "item_id long, text string")
    assert [(r["row"], r["item_id"]) for r in decontamination.leaks(docs, bench).collect()] == [(1, 5)]


def test_keep_one_keeps_the_first_of_each_group(odd_docs):
    kept = [r["doc_id"] for r in token_groups.keep_one(odd_docs).collect()]
    assert kept.count(1) == 1 and 2 not in kept and 3 not in kept
    assert {4, 5, 6, 7, 8} <= set(kept) and kept.count(None) == 2


def test_words_follow_the_contract(spark):
    df = spark.createDataFrame([("a b\x0bc \x1cd e",)], "t string")
    assert df.select(words_of(df["t"])).first()[0] == ["a b", "c", "\x1cd e"]
