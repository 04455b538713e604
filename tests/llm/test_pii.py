"""Entities against the contract's patterns, spans, disclosing terms, sanitising."""

from __future__ import annotations

import hashlib
import re

import pytest

from tracegraph.llm import pii_disclosure as pii

PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
TEXTS = [
    "a@b.c_d@e.f x@y.z-@q.r.s", "1.2.3.4.5.6.7.8 999.1.1.1 001.002.003.0004 é😀 1.2.3.4",
    "4111 1111 1111 1111  4111-1111-1111-1111x 1 2 3", "+1 (555) 123-4567 +12 +1(2) +49 30 1234567.",
    "", None, "a" * 30000 + "@", "1 2 " * 20000, "1." * 10000, "9" * 50000, "a@" * 10000 + "b.c", "+1" * 10000, "@a.b..c.d c@d.e.",
]


def _luhn(digits: str) -> bool:
    doubled = [int(c) * (1 + i % 2) for i, c in enumerate(reversed(digits))]
    return sum(d - 9 * (d > 9) for d in doubled) % 10 == 0


def brute(text: str | None) -> list[tuple[str, int, int]]:
    out = []
    for kind, p in PATTERNS.items():
        for m in re.finditer(p, text or ""):
            d = re.sub("[^0-9]", "", m.group())
            ok = {
                "email": True,
                "ip": kind != "ip" or all(int(x) <= 255 for x in m.group().split(".")),
                "card": 13 <= len(d) <= 19 and _luhn(d),
                "phone": 9 <= len(d) <= 15,
            }[kind]
            if ok:
                out.append((kind, m.start(), m.end()))
    return out


def test_query_against_brute_force(spark, sf):
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = pii.op7_pii_disclosure(spark, sf).collect()
    assert len(rows) == len(texts)
    for r in rows:
        spans = brute(texts[r["doc_id"]])
        assert [sum(k == x[0] for x in spans) for k in PATTERNS] == [r["n_email"], r["n_ip"], r["n_card"], r["n_phone"]]
        joined = ",".join(f"{k}:{a}:{z}" for k, a, z in spans)
        assert r["base_sha256"] == hashlib.sha256(joined.encode()).hexdigest()
        assert r["spans"].startswith(joined)


def test_hostile_texts(spark):
    df = spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string")
    rows = pii.protected(df, ["doc_id"]).collect()
    for r in rows:
        got = [(pii.KINDS[s["kind"]], s["start"], s["end"]) for s in r["__base"]]
        assert got == brute(TEXTS[r["doc_id"]])


@pytest.fixture
def badges(spark):
    rows = [(i, f"badge zz{i} Acme\\E12 mail u{i}@corp.example.org Acme\\E12\tx") for i in range(200)]
    rows += [(1000 + i, f"plain text number {i} mail") for i in range(3000)]
    return spark.createDataFrame(rows, "doc_id long, text string")


def test_disclosing_terms(spark, badges):
    rows = {r["doc_id"]: r for r in pii.sanitise(badges).collect()}
    assert rows[5]["text"] == "[TERM] zz5 [NUMBER] mail [EMAIL] [NUMBER]\t[TERM]"
    assert rows[1005]["text"] == "plain text number 5 mail"


def test_copies_prove_nothing(spark):
    rows = [(i, "secret words around one@copy.example.org here") for i in range(300)] + [(1000 + i, f"other {i}") for i in range(3000)]
    out = pii.sanitise(spark.createDataFrame(rows, "doc_id long, text string")).where("doc_id = 7").first()
    assert out["text"] == "secret words around [EMAIL] here"


def test_sanitise_keeps_columns_and_rows(spark):
    rows = [(1, "x a@b.cd y", "k", 10), (1, "x a@b.cd y", "k", 10), (None, None, None, None), (2, "", "__base", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, spans string, n_chars long")
    out = pii.sanitise(df)
    assert out.columns == df.columns
    assert sorted(map(str, out.collect())) == sorted(
        map(str, spark.createDataFrame([(1, "x [EMAIL] y", "k", 11)] * 2 + [(None, None, None, None), (2, "", "__base", 0)], df.schema).collect())
    )
    assert pii.sanitise(df.limit(0)).count() == 0


def test_handle_beside_one_address(spark):
    rows = [(i, f"note{i} by quill7 via q@one.example.org ok") for i in range(8)] + [(100 + i, f"note by other{i} via ok") for i in range(3000)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    out = {r["doc_id"]: r["text"] for r in pii.sanitise(df).collect()}
    assert out[3] == "note3 by [NUMBER] via [EMAIL] ok" and out[103] == "note by other3 via ok"


@pytest.mark.parametrize("copies", [1, 2, 150])
def test_copies_change_no_estimate(spark, copies):
    rows = [(i, f"badge mail u{i}@corp.example.org x{i}") for i in range(200)] + [(1000 + i, f"plain text {i} mail") for i in range(20_000)]
    rows += [(50_000 + i, rows[i % 200 if copies == 2 else 7][1]) for i in range({1: 0, 2: 200, 150: 149}[copies])]
    out = pii.sanitise(spark.createDataFrame(rows, "doc_id long, text string")).where("doc_id = 5").first()
    assert out["text"] == "[TERM] mail [EMAIL] x5"


def test_many_values_in_one_text_count_once(spark):
    rows = [(0, "lot " + " ".join(f"m{i}@corp.example.org" for i in range(200)))] + [(i, f"lot number {i}") for i in range(1, 200)]
    rows += [(1000 + i, f"plain {i}") for i in range(20_000)]
    out = pii.sanitise(spark.createDataFrame(rows, "doc_id long, text string")).where("doc_id = 0").first()
    assert out["text"].startswith("lot [EMAIL]")
