"""Mixing and the secret scan against plain Python, SQL and hand-made cases."""

import hashlib
import re

import duckdb
import pytest
from pyspark.sql import functions as F

from edgeblocks.llm import mixing, secrets

DDL = "doc_id long, text string, source string, extra string"


def docs(spark, rows):
    return spark.createDataFrame([(*r, "x") for r in rows], DDL)


def duck(small):
    c = duckdb.connect()
    c.sql(f"CREATE VIEW documents AS SELECT * FROM '{small}/documents.parquet'")
    c.sql(f"CREATE VIEW pages AS SELECT * FROM '{small}/pages.parquet'")
    return c


def test_mixing_equals_sql(spark, small):
    ours = sorted(map(tuple, mixing.op3_mixing(spark, small).select("doc_id", "size", "source_size", "target", "taken").collect()))
    theirs = sorted(duck(small).execute(f"SELECT doc_id, size, source_size, target, taken FROM ({mixing.SQL})").fetchall())
    assert ours == theirs


def test_mixing_budgets(spark):
    rows = [(i, "w " * (1 + i % 7), "abc"[i % 3]) for i in range(3000)] + [(9000, None, None), (9001, "a b c", None)]
    out = mixing.mix(docs(spark, rows)).toPandas()
    total = out["size"].sum()
    per = out.groupby(out["source"].fillna("~")).agg(size=("size", "sum"), taken=("taken", "sum"), target=("target", "first"))
    assert abs(per["target"].sum() - total) < 1e-6 and (per["target"] <= 3 * per["size"] + 1e-9).all()
    assert ((per["taken"] - per["target"]).abs() <= out["size"].max()).all()
    assert (out["taken"] <= 3 * out["size"]).all()
    again = mixing.mix(docs(spark, rows[::-1])).toPandas()
    assert sorted(map(tuple, out[["doc_id", "taken"]].values.tolist())) == sorted(map(tuple, again[["doc_id", "taken"]].values.tolist()))


def test_mixing_edges(spark):
    assert mixing.mix(docs(spark, [])).count() == 0
    assert [r.taken for r in mixing.mix(docs(spark, [(1, None, "a"), (None, "", None)])).collect()] == [0, 0]
    one = mixing.mix(docs(spark, [(1, "a b", "s"), (1, "a b", "s")])).collect()
    assert [r.taken for r in one] == [2, 2]
    applied = mixing.apply_mix(docs(spark, [(1, "a b", "s"), (2, "c", "s"), (None, "d", None)]))
    assert applied.columns == ["doc_id", "text", "source", "extra"] and applied.count() >= 1


def test_texts_without_words_obey_the_cap(spark):
    """Sources of which the first is taken three times over: no text is repeated oftener, and the mixed corpus holds what mix says."""
    rows = [(i, None if i % 5 == 0 else "", "a") for i in range(40)] + [(i, "w x y", "a") for i in range(40, 60)] + [(i, "w " * 300, "b") for i in range(60, 90)]
    table = docs(spark, rows)
    out = mixing.mix(table, weights=(5, 1)).collect()
    assert max(r.repeats for r in out) == 3 and max(r.repeats for r in out if not r.size) == 3
    got = {r.doc_id: r["count"] for r in mixing.apply_mix(table, weights=(5, 1)).groupBy("doc_id").count().collect()}
    assert got == {r.doc_id: r.repeats for r in out if r.repeats}
    plan = mixing.apply_mix(table)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" not in plan and "Exchange hashpartitioning" not in plan


BASE = {
    "assign": (re.compile(r"""((?:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I), 2, 8),
    "access": (re.compile(r"AKIA[A-Z0-9]+"), 0, 16), "hex": (re.compile(r"[0-9a-f]+"), 0, 32),
}


def plain_spans(text):
    out = []
    for i, (kind, (p, g, n)) in enumerate(BASE.items()):
        out += [(m.start(), i, m.end(), kind) for m in p.finditer(text or "") if len(m[g]) >= n]
    return sorted(out)


TEXTS = [
    None, "", "é🙂 password = 'hunter2hunter2' tail", "token=secret=abcdefgh1 API_KEY: \"abcdefghij\"", "token=token:abcdefghij", "AKIA" + "Z" * 12 + " AKIA123 xAKIA" + "Q" * 20, "f" * 31 + " " + "0a" * 16 + "g" + "1" * 40,
    "password=" + "0123456789abcdef" * 3, "secret:short apikey=longenough", "x" * 5000 + " passwd:abcdefgh", "Aa1" * 9 + " and Bb2" * 1, "token\n=\nabcdefghij", "ſecret=abcdefghij",
]


def test_secret_spans(spark):
    got = {r.doc_id: r for r in secrets.scan_secrets(docs(spark, [(i, t, "s") for i, t in enumerate(TEXTS)])).collect()}
    for i, t in enumerate(TEXTS):
        if t and "ſ" in t:
            assert got[i].n_assign == 0
            continue
        want = plain_spans(t)
        assert [got[i].n_assign, got[i].n_access, got[i].n_hex] == [sum(k == w[3] for w in want) for k in BASE]
        joined = ",".join(f"{k}:{a}:{b}" for a, _, b, k in want)
        assert got[i].base_sha256 == hashlib.sha256(joined.encode()).hexdigest()
        assert set(joined.split(",")) <= set(got[i].spans.split(",")) | {""}


def test_ownership(spark):
    shared, own, generic = "password=commonvalue1", "password=onlymine99", "Zx9Zx9Zx9Zx9Zx9Zx9Zx9Q"
    rows = [(i, shared, f"s{i % 5}") for i in range(50)] + [(100, own, "s1"), (101, own, "s1"), (102, generic, "s2"), (103, None, None)]
    got = {r.doc_id: r for r in secrets.scan_secrets(docs(spark, rows)).collect()}
    assert (got[0].n_live, got[0].n_copied) == (0, 1) and (got[100].n_live, got[100].n_copied) == (1, 0)
    assert got[102].spans == f"generic:0:{len(generic)}" and got[102].n_assign == 0
    counts = {r.owners: r.repos for r in secrets.ownership(secrets.scanned(docs(spark, rows))).collect()}
    assert counts[5] == 50
    clean = {r.doc_id: r.text for r in secrets.redact(docs(spark, rows)).collect()}
    assert clean[0] == shared and clean[100] == "<secret>" and clean[103] is None and len(clean) == len(rows)


def test_secret_edges(spark):
    assert secrets.scan_secrets(docs(spark, [])).count() == 0
    twice = docs(spark, [(1, "a token=abcdefgh1 b", "s"), (1, "a token=abcdefgh1 b", "s"), (None, "secret: abcdefgh2", None)])
    assert secrets.redact(twice).count() == 3 and secrets.redact(twice).columns == ["doc_id", "text", "source", "extra"]
    assert sorted(r.text for r in secrets.redact(twice).collect()) == ["<secret>", "a <secret> b", "a <secret> b"]


def test_redaction_of_values_in_few_copies(spark):
    """A value in two sources, or in many documents of few sources, goes; one that many of both hold stays."""
    few, narrow, wide = "token=abcdefgh1", "token=abcdefgh2", "token=abcdefgh3"
    rows = [(i, few, f"s{i}") for i in range(2)] + [(10 + i, narrow, f"s{i % 3}") for i in range(30)] + [(50 + i, wide, f"s{i % 6}") for i in range(30)]
    clean = {r.doc_id: r.text for r in secrets.redact(docs(spark, rows)).collect()}
    assert all(t == (wide if i >= 50 else "<secret>") for i, t in clean.items()) and len(clean) == len(rows)


def test_native_plans(spark, small):
    for run in (mixing.op3_mixing, secrets.op8_secrets):
        plan = run(spark, small)._jdf.queryExecution().toString()
        assert not re.search("Python|Arrow|Pandas", plan)


@pytest.mark.parametrize("text, n", [(None, 0), ("", 0), (" \t\n", 0), ("a", 1), ("a\x0bb\xa0c d", 3)])
def test_word_count(spark, text, n):
    assert spark.createDataFrame([(text,)], "t string").select(mixing.word_count(F.col("t"))).first()[0] == n
