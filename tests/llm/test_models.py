"""Encoders, searchers and classifiers: exact against the library or brute force, accuracy on held-out documents."""

import struct
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_native import docs

from edgeblocks.llm import ann, bm25, bpe, langid, licenses, toxicity

SPEC = bpe.tokenizer_json()


# ---- encoding

@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_str(SPEC)


ODD = [
    "", " ", "Hello, World's don't 12 ½", "<|endoftext|>abc<|startoftext|> x <|end", "ΣΑΣ Σ İstanbul", "中文 test 日本", "é ẛ̣", "x" * 900, "a　b\x85c\xa0d\x1ce", "🙂 ok", "naïve café ÜBER straße",
    "".join(chr(c) for c in range(1, 0x530)), "".join(chr(c) + " " for c in range(0x1E00, 0x2100)),
]


def test_encoder_equals_library(library):
    lexicon = bpe.compile_lexicon(["hello", "world", "the", "test", "über", "straße", "ab", "abc", "abd", "b"], SPEC)
    for enc in (bpe.Encoder(SPEC, lexicon), bpe.Encoder(SPEC, None)):
        for text, raw in zip(ODD, enc.encode_all(ODD)):
            ids = library.encode(text, add_special_tokens=False).ids
            assert raw == struct.pack(f"<{len(ids)}I", *ids), text[:40]
            assert enc.decode(raw) == library.decode(ids, skip_special_tokens=False)


def test_encoder_forgets(library, monkeypatch):
    monkeypatch.setattr(bpe, "REMEMBERED", 5)
    enc = bpe.Encoder(SPEC, None)
    text = " ".join(f"word{i}x" for i in range(40))
    for _ in range(2):
        assert enc.encode(text) == struct.pack(f"<{len(i)}I", *i) if (i := library.encode(text, add_special_tokens=False).ids) else False


def test_automaton():
    words = sorted({w.encode() for w in ["", "a", "ab", "abc", "xbc", "xb", "résumé", "zz"]})
    auto = bpe.Automaton.build(words)
    assert auto.ranks(words).tolist() == list(range(len(words)))
    assert auto.ranks([b"abcd", b"b", b"x", "ré".encode()]).tolist() == [-1] * 4
    many = sorted({f"{p}{s}".encode() for p in range(300) for s in ("ing", "ed", "s")})
    big = bpe.Automaton.build(many)
    assert big.ranks(many).tolist() == list(range(len(many))) and len(big.final) < 500  # endings are shared
    assert bpe.Automaton.build([]).ranks([b"a"]).tolist() == [-1]
    back = bpe.unpack(bpe.pack([big.keys, big.targets, big.outputs, big.final]))
    assert all((x == y).all() for x, y in zip(back, (big.keys, big.targets, big.outputs, big.final)))


def test_encode_table(spark, library, small):
    import hashlib

    rows = [(1, "Hello World", "s"), (1, "Hello World", "s"), (None, "x", None), (2, None, "s"), (3, "", "s")]
    got = bpe.encode(docs(spark, rows)).collect()
    assert sorted(r.n_tokens for r in got) == [0, 0, 1, 2, 2] and bpe.encode(docs(spark, [])).count() == 0
    whole = {r.doc_id: r for r in bpe.op10_bpe(spark, small).collect()}
    for r in spark.read.parquet(f"{small}/documents.parquet").collect():
        ids = library.encode(r.text or "", add_special_tokens=False).ids
        assert whole[r.doc_id].n_tokens == len(ids) and whole[r.doc_id].ids_sha256 == hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest()
        assert whole[r.doc_id].decoded_sha256 == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()


# ---- nearest neighbours

def nearest(x, ids, q, k):
    d = np.sqrt(((x - x[q]) ** 2).sum(axis=1))
    d[ids == ids[q]] = np.inf
    o = np.lexsort((ids, d))
    return [(int(ids[i]), float(d[i])) for i in o[:k] if d[i] < np.inf]


def test_ann_recall(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(6000, 64)).astype(np.float32)
    x[1000:1400] = x[0]  # a group of copies
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = ann.search(df, F.col("vec_id") % 100 == 0, pack=40).collect()
    by = {}
    for r in sorted(got, key=lambda r: (r.query_id, r.rank)):
        by.setdefault(r.query_id, []).append((r.vec_id, r.score))
    ids, wide, hits, total = np.arange(6000), x.astype(float), 0, 0
    assert len(by) == 60
    for q, found in by.items():
        want = nearest(wide, ids, q, 10)
        assert all(abs(s - np.sqrt(((wide[v] - wide[q]) ** 2).sum())) == 0 for v, s in found)
        hits += len({v for v, _ in want} & {v for v, _ in found})
        total += 10
        if q == 0 or 1000 <= q < 1400:
            assert found == want
    assert hits / total >= 0.9


def test_nearest_query_equals_sql(spark):
    import duckdb

    d = "/root/testdata/sf0.01"
    c = duckdb.connect()
    c.sql(f"CREATE VIEW embeddings AS SELECT * FROM '{d}/embeddings.parquet'")
    ours = sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in ann.op2_nearest(spark, d).collect())
    assert ours == sorted(c.execute(ann.SQL).fetchall()) and len(ours) == 50


def test_ann_edges(spark):
    rows = [(0, [1.0, 0.0]), (0, [1.0, 0.0]), (100, [1.0, 0.0]), (7, [0.0, 2.0]), (8, None), (9, [0.0, 0.0]), (10, [float("nan"), 1.0]), (11, [1.0, None]), (12, [1.0]), (None, [1.0, 1.0])]
    df = spark.createDataFrame([(*r, "x") for r in rows], "vec_id long, embedding array<float>, rank string")
    got = sorted((r.query_id, r.rank, r.vec_id, r.score) for r in ann.search(df, F.col("vec_id") % 100 == 0).collect())
    assert got == [(0, 1, 100, 0.0), (0, 2, 7, 5**0.5), (100, 1, 0, 0.0), (100, 2, 7, 5**0.5)]
    assert ann.search(df.limit(0), F.col("vec_id") % 100 == 0).count() == 0


def test_dense_group_over_full_blocks():
    """A third of near-equal vectors: each block of 4096 still holds all of a query's nearest after the scan."""
    rng = np.random.default_rng(2)
    x = rng.normal(size=(3 * 4096, 64))
    x[::3] = x[0] + 0.01 * rng.normal(size=(4096, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    book, q = ann.Codebook.fit(x[:4096]), x[:60]
    for lo in range(0, len(x), 4096):
        block = x[lo : lo + 4096]
        found = ann.scan(book, q, block, book.encode(block), 64, 10)
        for i, near in enumerate(found):
            d = ((block - q[i]) ** 2).sum(axis=1)
            assert set(np.argsort(d, kind="stable")[:11]) <= set(near.tolist())
    assert np.mean([len(n) for n in found]) < 4096



def test_anisotropic_codes_cut_the_parallel_error():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(3000, 32))
    book = ann.Codebook.fit(x)
    a = ann._augmented(x) - book.shift
    u = a / np.linalg.norm(a, axis=1, keepdims=True)

    def parallel(codes):
        back = np.concatenate([book.centres[j][codes[:, j]] for j in range(codes.shape[1])], axis=1)
        return (((a - back) * u).sum(axis=1) ** 2).mean()

    assert book.weight > 1 and parallel(book._assign(a)) < parallel(book._nearest(a))


# ---- search

def test_bm25_equals_brute_force(spark):
    rng = np.random.default_rng(5)
    vocab = [f"t{i}" for i in range(60)]
    p = 1 / np.arange(1, 61)
    texts = [" ".join(rng.choice(vocab, rng.integers(0, 40), p=p / p.sum())) for _ in range(700)]
    texts[10], texts[11], texts[100], texts[200] = None, "", texts[0], "Only, here!"
    df = docs(spark, [(i, t, "s") for i, t in enumerate(texts)] + [(None, "t1", "s")])
    got = {}
    for r in bm25.search(df, F.col("doc_id") % 100 == 0, shard=128, pack=4).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.doc_id, r.score))
    tf = [dict(zip(*(x.tolist() for x in bm25.terms_of(t)))) for t in texts]
    size = np.array([sum(t.values()) for t in tf])
    mean, n = size.sum() / len(texts), len(texts)
    df_ = {}
    for t in tf:
        for w in t:
            df_[w] = df_.get(w, 0) + 1
    for q in range(0, 700, 100):
        s = np.array([sum(np.log1p((n - df_[w] + 0.5) / (df_[w] + 0.5)) * t[w] * 2.2 / (t[w] + 1.2 * (0.25 + 0.75 * l / mean)) for w in tf[q] if w in t) for t, l in zip(tf, size)])
        o = [i for i in np.lexsort((np.arange(n), -np.round(s, 10)))[:10] if s[i] > 0]
        assert [d for d, _ in got.get(q, [])] == o and np.allclose([x for _, x in got.get(q, [])], s[o])
    assert bm25.search(docs(spark, []), F.col("doc_id") % 100 == 0).count() == 0
    assert bm25.search(docs(spark, [(100, None, "s")]), F.col("doc_id") % 100 == 0).count() == 0


def test_blocks_are_skipped():
    """Documents of eight kinds of words: a query's own kind is searched, most blocks of the others are never read, and nothing is lost."""
    rng = np.random.default_rng(3)
    texts = [" ".join([f"k{i % 8}"] * 9 + [f"k{i % 8}w{x}" for x in rng.zipf(1.5, 30)] + [f"c{x}" for x in rng.zipf(1.3, 4)]) for i in range(4000)]
    got = [bm25.terms_of(t) for t in texts]
    sizes = np.array([int(c.sum()) for _, c in got])
    pick = list(range(0, 4000, 100))
    q = bm25.Queries(np.array(pick), np.concatenate([got[i][0] for i in pick]), np.array([len(got[i][0]) for i in pick]))
    at, known = q.number(np.concatenate([t for t, _ in got]))
    q.weigh(np.bincount(at[known], minlength=len(q.vocabulary)), 4000, sizes.mean())
    s = bm25.Shard(q, np.arange(4000), np.concatenate([t for t, _ in got]), np.concatenate([c for _, c in got]), np.array([len(t) for t, _ in got]), sizes)
    for i in range(len(pick)):
        terms, weights = q.of(i)
        s.weights[terms] = weights
        every = s.full(np.arange(4000))
        s.weights[terms] = 0
        before = s.skipped
        docs_, scores = s.best(terms, weights, 10, 0.0)
        edge = np.sort(every)[-10]
        assert set(np.flatnonzero(every >= edge)) <= set(docs_.tolist()) and np.array_equal(scores, every[docs_])
        assert s.skipped > before
        assert len(s.best(terms, weights, 10, every.max() * 2)[0]) == 0
    assert s.skipped > 0.6 * 2 * len(pick) * s.blocks


def test_queries_side_by_side():
    """Queries of one kind that go over a shard together find what each finds alone, near ties below single precision too, and skip blocks."""
    rng = np.random.default_rng(4)
    texts = [" ".join([f"k{i % 4}"] * 5 + [f"k{i % 4}w{x}" for x in rng.zipf(1.4, 40)] + [f"c{x}" for x in rng.zipf(1.3, 4)]) for i in range(3000)]
    texts[40:400:4] = [" ".join(["k0"] * 20000 + [f"y{i}y{x}" for x in range(i)]) for i in range(90)]
    got = [bm25.terms_of(t) for t in texts]
    sizes = np.array([int(c.sum()) for _, c in got])
    pick = [*range(0, 800, 40), 1, 2, 3]
    q = bm25.Queries(np.array(pick), np.concatenate([got[i][0] for i in pick]), np.array([len(got[i][0]) for i in pick]))
    at, known = q.number(np.concatenate([t for t, _ in got]))
    q.weigh(np.bincount(at[known], minlength=len(q.vocabulary)), 3000, sizes.mean())
    s = bm25.Shard(q, np.arange(3000), np.concatenate([t for t, _ in got]), np.concatenate([c for _, c in got]), np.array([len(t) for t, _ in got]), sizes)
    assert 0 < s.columns < len(s.sizes) and s.block_table.shape[1] > s.columns  # lists inside and outside both tables
    every = np.zeros((len(pick), 3000))
    for i in range(len(pick)):
        s.weights[q.of(i)[0]] = q.of(i)[1]
        every[i] = s.full(np.arange(3000))
        s.weights[q.of(i)[0]] = 0
    edges = np.sort(every, axis=1)[:, -10]
    best = np.sort(every[1])[-20:]  # of the query k0
    assert ((np.diff(best) > 0) & (np.diff(best) < best[1:] * 2.0**-23)).any()  # scores that single precision hardly tells apart
    for floors in (np.zeros(len(pick)), edges, np.where(np.arange(len(pick)) % 2, edges, 0), edges * 0.9):
        s.skipped = 0
        for i, (found, scores) in enumerate(s.best_of([q.of(i) for i in range(len(pick))], 10, floors)):
            assert sorted(found.tolist()) == np.flatnonzero(every[i] >= edges[i]).tolist() and np.array_equal(scores, every[i][found])
        for i in range(0, 20, 5):
            s.best(*q.of(i), 10, floors[i])
        assert s.skipped > 0
    assert all(not len(found) for found, _ in s.best_of([q.of(0), q.of(1)], 10, every.max() * np.array([2, 2])))


# ---- language

def test_languages_of_held_out_documents(spark):
    d = "/root/testdata/sf0.01"
    got = langid.op5_langid(spark, d).join(spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert len(got) > 200 and (got["lang"] == got["lang_pred"]).mean() > 0.95 and got["score"].between(0, 1).all()


def test_language_spans_and_edges(spark):
    train = [(i, "the quick brown fox jumps over the lazy dog again", "s", "en") for i in range(5)] + [(i, "быстрая лиса прыгает через собаку", "s", "ru") for i in range(5)] + [(9, "x", "s", None), (9, None, "s", "en")]
    df = spark.createDataFrame(train, "doc_id long, text string, source string, lang string")
    model = langid.fit(df)
    assert model.langs == ["en", "ru"]
    text = "the lazy dog over the quick fox " * 3 + "лиса прыгает через собаку " * 2
    rows = docs(spark, [(1, text, "s"), (2, None, "s"), (3, "123 !?", "s"), (4, "中文", "s"), (1, text, "s"), (None, "собаку", "s")])
    got = langid.predict(rows, model, keep_spans=True).collect()
    by = {r.doc_id: r for r in got}
    assert len(got) == 6 and (by[2].lang_pred, by[2].score) == ("und", 0.0) and by[3].lang_pred == "und" and by[4].lang_pred == "en" and by[None].lang_pred == "ru"
    assert [s.lang for s in by[1].spans] == ["en", "ru"] and by[1].spans[1].start == text.index("лиса") and by[1].lang_pred == "en"
    nothing = langid.fit(df.limit(0))
    assert {r.lang_pred for r in langid.predict(rows, nothing).collect()} == {"und"}
    assert langid.predict(rows.limit(0), model).count() == 0


def test_viterbi_against_all_paths():
    import itertools

    rng = np.random.default_rng(2)
    per = np.array([3, 0, 5, 1, 4])
    e = rng.normal(size=(per.sum(), 3)).astype(np.float32) * 3
    got, at = langid.viterbi(e, per, 2.0), 0
    for n in per:
        score = lambda p, at=at, n=n: sum(e[at + i, p[i]] for i in range(n)) - 2.0 * sum(x != y for x, y in zip(p, p[1:]))
        best = max(itertools.product(range(3), repeat=int(n)), key=score)
        assert np.isclose(score(tuple(got[at : at + n])), score(best), atol=1e-4)
        at += n


# ---- toxicity

def test_toxic_documents_of_unseen_ids(spark):
    d = "/root/testdata/sf0.1"
    labels, texts = spark.read.parquet(f"{d}/labels.parquet"), spark.read.parquet(f"{d}/documents.parquet")
    chain = toxicity.fit(texts, labels.where("doc_id % 5 <> 0"), sample=3000)
    got = toxicity.predict(texts.join(labels.where("doc_id % 5 = 0").select("doc_id"), "doc_id"), chain).join(labels.select("doc_id", F.col("toxic").alias("label")), "doc_id").toPandas()
    hit = (got["toxic"] & (got["label"] == 1)).sum()
    assert hit / (got["label"] == 1).sum() > 0.85 and hit / got["toxic"].sum() > 0.85


def test_chain_uses_earlier_categories():
    rng = np.random.default_rng(0)
    first = rng.integers(0, 2, 400)
    words = [np.unique(np.append(rng.integers(10, 60, 5), 1 if f else 2)).astype(np.int32) for f in first]
    noise = rng.random(400) < 0.05
    labels = np.stack([first, first ^ noise], axis=1)
    chain = toxicity.fit_chain(words, np.zeros((400, toxicity.MEASURES)), labels, ["a", "b"])
    assert len(chain.models) == 2 and chain.models[1].weights[-1] > 0.1  # the weight of the earlier log-odds
    assert not toxicity.fit_chain(words, np.zeros((400, toxicity.MEASURES)), np.zeros((400, 2), int), ["a", "b"]).models


def test_toxicity_edges(spark):
    labels = spark.createDataFrame([(1, 1, 0), (1, 0, 0), (2, 1, 1), (None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")
    df = docs(spark, [(1, "good text", "s"), (2, "bad text", "s"), (3, None, "s"), (None, "", "s"), (2, "bad text", "s")])
    out = toxicity.predict(df, toxicity.fit(df, labels)).collect()
    assert len(out) == 5 and not any(r.toxic for r in out if r.doc_id in (3, None))
    assert toxicity.predict(df, toxicity.fit(df, labels.limit(0))).where("toxic").count() == 0
    assert toxicity.reject(df, labels.limit(0)).columns == df.columns and toxicity.reject(df.limit(0), labels).count() == 0


# ---- licenses

def plain_licenses(text, reach=None):
    """Templates of which some stretch of the text holds enough shingles: stretches of the template's own length, or as long as reach says."""
    words = lambda t: (t or "").lower().encode().translate(licenses._PLAIN).split()
    out = set()
    for name, template in licenses.TEMPLATES.items():
        w, t = words(text), words(template)
        n = min(licenses.SHINGLE, len(t))
        own = {tuple(t[i : i + n]) for i in range(len(t) - n + 1)}
        grams = [tuple(w[i : i + n]) for i in range(len(w) - n + 1)]
        if len(set(grams) & own) / len(own) < licenses.CONTAINMENT:
            continue
        length = len(t) - n + 1 if reach is None else reach[name]
        held, common = Counter(), 0  # of the stretch that slides along
        for i, g in enumerate(grams):
            held[g] += 1
            common += held[g] == 1 and g in own
            if i >= length:
                old = grams[i - length]
                held[old] -= 1
                common -= held[old] == 0 and old in own
            if common / len(own) >= licenses.CONTAINMENT:
                out.add(name)
                break
    return out


def test_licenses_equal_plain_scan(spark):
    rng = np.random.default_rng(4)
    filler = lambda n: " ".join(f"w{i}" for i in rng.integers(0, 500, n))
    texts = [None, "", "short", "All rights", *licenses.TEMPLATES.values()]
    for name, template in licenses.TEMPLATES.items():
        t = template.split()
        texts += [f"{filler(40)} {template.upper()} {filler(33)}", f"{filler(int(rng.integers(0, 300)))} {' '.join(t[: len(t) // 2])} zzz {' '.join(t[len(t) // 2 + 1 :])} {filler(9)}", " ".join(t[: len(t) // 2])]
    got = {}
    for r in licenses.scan(docs(spark, [(i, t, "s") for i, t in enumerate(texts)])).collect():
        got.setdefault(r.doc_id, set()).add(r.license_id)
    # a window is longer than the template by up to a stride, so it may hold a little more than a stretch of the template's own length
    wide = {name: -(-c.window // c.stride) * c.stride for c in licenses.classes() for name in c.names}
    for i, t in enumerate(texts):
        assert plain_licenses(t) <= got.get(i, set()) <= plain_licenses(t, reach=wide), t
        if i < 4:
            assert i not in got
    assert licenses.scan(docs(spark, [])).count() == 0
    assert len(licenses.TEMPLATES) >= 40 and all(c.rows > 1 for c in licenses.classes())


def test_license_windows_do_not_depend_on_the_slice():
    texts = [f"{'a b c ' * i} Released under the MIT License. x y" for i in range(20)]
    cs = licenses.classes()
    together = [(t, *rest) for t, *rest in licenses.matches(texts, cs)]
    assert together == [(i, *rest) for i, t in enumerate(texts) for _, *rest in licenses.matches([t], cs)]


def test_bands():
    for s in (0.1, 0.5, 0.8):
        b = licenses.bands_for(s, 2, 0.99)
        assert 1 - (1 - s**2) ** b >= 0.99 > 1 - (1 - s**2) ** (b - 1)


def test_chain_skips_a_constant_category():
    """A category of one class is left out of the fit; the others are found all the same."""
    rng = np.random.default_rng(0)
    y = np.arange(200) % 2
    found = [np.unique(np.append(rng.integers(10, 400, 12), 5 if t else 6)).astype(np.int32) for t in y]
    for first in (0, 1):
        chain = toxicity.fit_chain(found, np.zeros((200, toxicity.MEASURES)), np.stack([np.full(200, first), y], axis=1), ["a", "b"])
        last = chain.models[-1]
        z = np.array([last.logit(f, np.zeros(toxicity.MEASURES + 1)) for f in found])
        assert ((1 / (1 + np.exp(-z)) > chain.cut) == (y == 1)).all() and chain.models[0].constant
    none = toxicity.fit_chain(found, np.zeros((200, toxicity.MEASURES)), np.stack([y, np.ones(200, int)], axis=1), ["a", "b"])
    assert none.cut == 1.0


def test_two_hundred_languages():
    """Labels of many languages keep their numbers."""
    e = np.full((400, 200), -5.0, np.float32)
    e[np.arange(400), np.arange(400) % 200] = 50
    labels = langid.viterbi(e, np.array([1] * 200 + [200]))
    assert labels.tolist() == [i % 200 for i in range(400)]


# ---- whole queries against plain versions

def plain_words(text):
    """(letters with their neighbours, script of the first, length) of each word."""
    low, out, word = f" {(text or '').lower()} ", [], []
    for i in range(1, len(low)):
        if low[i].isalpha():
            word.append(tuple(ord(c) if c.isalpha() else 32 for c in low[i - 1 : i + 2]))
        elif word:
            out.append((word, max((s, n) for s, n in langid.SCRIPTS if s <= word[0][1])[1], len(word)))
            word = []
    return out


def plain_bucket(context):
    x = 0
    for c, m in zip(context, (0x9E3779B1, 0x85EBCA6B, 0xC2B2AE35)):
        x ^= c * m & 0xFFFFFFFF
    x = (x ^ x >> 15) * 0x2C1B3C6D & 0xFFFFFFFF
    return (x >> 16) % langid.BUCKETS


def test_language_query_equals_plain_version(spark, small):
    """Counts, scripts, scores and the best path of every document, on dictionaries."""
    import zlib

    rows = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text", "lang").collect()
    held = {r.doc_id: zlib.crc32(str(r.doc_id).encode()) % 3 == 1 for r in rows}
    grams, scripts = {}, {}
    for r in rows:
        if not held[r.doc_id] and r.lang is not None and r.text is not None:
            for word, script, n in plain_words(r.text):
                scripts.setdefault(r.lang, Counter())[script] += n
                grams.setdefault(r.lang, Counter()).update(plain_bucket(c) for c in word)
    langs = sorted(grams)
    total = {x: sum(grams[x].values()) + 0.1 * langid.BUCKETS for x in langs}
    logs = {x: {b: np.float32(np.log((n + 0.1) / total[x])) for b, n in grams[x].items()} for x in langs}
    none = {x: np.float32(np.log(0.1 / total[x])) for x in langs}
    may = {x: {n for n, c in scripts[x].items() if c / sum(scripts[x].values()) >= langid.SCRIPT_SHARE} for x in langs}
    got = {r.doc_id: r for r in langid.op5_langid(spark, small).collect()}
    assert len(got) == len(rows)
    close = 0
    for r in rows:
        words = plain_words(r.text)
        if not words:
            assert (got[r.doc_id].lang_pred, got[r.doc_id].score) == ("und", 0.0)
            continue
        best, back = {x: 0.0 for x in langs}, []
        for word, script, _ in words:
            any_ = any(script in may[x] for x in langs)
            lead = max(langs, key=lambda x: (best[x], -langs.index(x)))
            came = {x: x if best[x] >= best[lead] - langid.SWITCH else lead for x in langs}
            gain = {x: (0.0 if not any_ else sum(float(logs[x].get(plain_bucket(c), none[x])) for c in word) if script in may[x] else -1e4) for x in langs}
            best = {x: max(best[x], best[lead] - langid.SWITCH) + gain[x] for x in langs}
            back.append(came)
        at, mass = max(langs, key=lambda x: (best[x], -langs.index(x))), Counter()
        for (_, _, n), came in zip(reversed(words), reversed(back)):
            mass[at] += n
            at = came[at]
        want = max(langs, key=lambda x: (mass[x], -langs.index(x)))
        same = got[r.doc_id].lang_pred == want and abs(got[r.doc_id].score - mass[want] / sum(mass.values())) < 0.02
        close += same
        assert got[r.doc_id].held_out == held[r.doc_id]
    assert close >= 0.99 * sum(bool(plain_words(r.text)) for r in rows)  # sums in single precision may turn a word at the edge of two spans


def test_toxicity_query_equals_plain_version(spark, small):
    """Features, log-odds and the flag of every document from the fitted weights, on dictionaries."""
    import math
    import re
    import zlib

    df = spark.read.parquet(f"{small}/documents.parquet")
    chain = toxicity.fit(df, spark.read.parquet(f"{small}/labels.parquet"))
    tables = [dict(zip(m.words.tolist(), m.weights[: len(m.words)].tolist())) for m in chain.models]
    got = {r.doc_id: r for r in toxicity.op6_toxicity(spark, small).collect()}
    flagged = 0
    for r in df.select("doc_id", "text").collect():
        raw = (r.text or "").lower().encode()
        words = re.findall(rb"[a-z0-9\x80-\xff]+", raw)
        if not words:
            assert (got[r.doc_id].p_toxic, got[r.doc_id].toxic) == (0.0, False)
            continue
        marks = set(words) | {w[:n] + b"~" for w in words for n in toxicity.STEMS if len(w) > n}
        buckets = {zlib.crc32(w) % toxicity.BUCKETS for w in marks}
        blank = sum(raw.count(c) for c in (b" ", b"\n", b"\t", b"\r"))
        dense = [math.log1p(len(words)) / 10, len(set(words)) / len(words), (len(raw) - sum(map(len, words)) - blank) / len(raw)]
        for model, table in zip(chain.models, tables):
            z = sum(table.get(b, 0.0) for b in buckets) + sum(w * x for w, x in zip(model.weights[len(model.words) :], dense)) + model.bias
            dense.append(max(-30.0, min(30.0, z)))
        p = [1 / (1 + math.exp(-z)) for z in dense[toxicity.MEASURES :]]
        row = got[r.doc_id]
        assert abs(row.p_low_quality - p[0]) < 1e-6 and abs(row.p_toxic - p[1]) < 1e-6
        assert row.toxic == (p[1] > chain.cut) or abs(p[1] - chain.cut) < 1e-6
        flagged += row.toxic
    assert 0 < flagged < len(got) / 2
