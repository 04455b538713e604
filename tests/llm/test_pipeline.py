"""The pipeline from end to end, each stage against what the stage before kept."""

from __future__ import annotations

import hashlib

import public_tokenizers
from tokenizers import Tokenizer

import corpus_pipeline as cp
from tracegraph.llm.common import materialise, table


def test_pipeline_end_to_end(spark, sf):
    docs, kept = table(spark, sf, "documents"), []
    names = docs.columns
    for name, stage in cp.STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf), f"test-{name}")
        assert docs.columns == names
        kept.append({r["doc_id"]: r["text"] for r in docs.collect()})
    raw = {r["doc_id"]: r["text"] for r in table(spark, sf, "documents").collect()}
    quality, unique, clean, private = kept
    assert set(raw) > set(quality) > set(unique) >= set(clean) == set(private)
    assert all(quality[i] == raw[i] for i in quality) and all(clean[i] == unique[i] for i in clean)
    # one document of every group of equal texts stays, the first one
    first = {}
    for i in sorted(quality):
        first.setdefault(hashlib.sha1(quality[i].lower().encode()).digest(), i)
    assert set(unique) <= set(first.values())
    items = [r["text"] for r in table(spark, sf, "benchmark").collect()]
    assert not any(b and b in t for t in clean.values() for b in items)
    assert not any("@" in w and "." in w.split("@")[1] for t in private.values() for w in t.split() if w.count("@") == 1 and w[0] != "@" and w.split("@")[1][:1].isalnum())
    rows = cp.STAGES[-1][1](spark, docs, sf).collect()
    slow = Tokenizer.from_file(public_tokenizers.path(cp.TOKENIZER))
    tokens = {i: len(slow.encode(t, add_special_tokens=False).ids) + 1 for i, t in private.items()}
    placed: dict[int, int] = {}
    for r in rows:
        placed[r["doc_id"]] = placed.get(r["doc_id"], 0) + r["length"]
    assert placed == tokens
    whole = {(r["doc_id"], r["start"]): r["ids_crc32"] for r in cp.run(spark, sf).collect()}
    assert whole == {(r["doc_id"], r["start"]): r["ids_crc32"] for r in rows}


def test_pipeline_of_nothing(spark, tmp_path, sf):
    for name in ("documents", "benchmark"):
        table(spark, sf, name).limit(0).write.parquet(f"{tmp_path}/{name}.parquet")
    assert cp.run(spark, str(tmp_path)).count() == 0
