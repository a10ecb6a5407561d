"""SimHash against brute force, WARC packages by round trip."""

import hashlib
import io
import re
import zipfile

import numpy as np
import pytest
import xxhash
from test_native import docs, duck

from edgeblocks.llm import simhash, warc

WORD = re.compile("[^\x20\x09-\x0d]+")


def plain_fingerprint(text):
    words = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(fps):
    parent = {i: i for i in fps}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(fps)
    for i in ids:
        for j in ids:
            if i < j and (fps[i] ^ fps[j]).bit_count() <= 3:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


TEXTS = [None, "", "One", "one two", "Ünï Öne TWO three", "a b c d " * 500, "a b c d " * 501, "x\x0by z", *(" ".join(f"w{(i * j) % 97}" for j in range(80)) for i in range(12))]
TEXTS += [TEXTS[-1], TEXTS[-1] + " tail", TEXTS[-2].upper(), " ".join(f"v{j}" for j in range(70000))]


@pytest.mark.parametrize("group", [4096, 2])
def test_simhash(spark, monkeypatch, group):
    monkeypatch.setattr(simhash, "GROUP", group)
    fps = {i: plain_fingerprint(t) for i, t in enumerate(TEXTS)}
    got = {r.doc_id: r for r in simhash.components(docs(spark, [(i, t, "s") for i, t in enumerate(TEXTS)])).collect()}
    assert {i: got[i].fp & (1 << 64) - 1 for i in fps} == fps
    assert {i: got[i].component_id for i in fps} == plain_components(fps)


def test_forest_keeps_every_link():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 62, 5, dtype=np.int64).astype(np.uint64)
    fps = np.unique(np.concatenate([b ^ (np.uint64(1) << rng.integers(0, 64, 40).astype(np.uint64)) for b in base]))
    a, b = simhash.forest(fps)
    assert (np.bitwise_count(a ^ b) <= 6).all() and len(np.unique(a)) == 5 and len(a) == len(fps) - 5


def test_key_masks():
    masks = simhash._key_masks()
    assert len(masks) == 20 and all(len(simhash._finer_masks(m)) == 56 for m in masks)
    rng = np.random.default_rng(0)
    for _ in range(200):
        x = int(rng.integers(0, 1 << 62))
        y = x
        for bit in rng.integers(0, 64, 3):
            y ^= 1 << int(bit)
        shared = [m for m in masks if x & m == y & m]
        assert shared and all(any(x & f == y & f for f in simhash._finer_masks(m)) for m in shared)


def test_dedup(spark):
    rows = [(5, "a b c d e", "s"), (5, "a b c d e", "s"), (3, "A B C D E", "s"), (9, "q r s t u v", "s"), (None, "lone text here", "s")]
    kept = simhash.dedup(docs(spark, rows))
    assert kept.columns == ["doc_id", "text", "source", "extra"]
    assert sorted(r.doc_id if r.doc_id is not None else -1 for r in kept.collect()) == [-1, 3, 9]
    assert simhash.dedup(docs(spark, [])).count() == 0 and simhash.components(docs(spark, [])).count() == 0


def test_dedup_of_scattered_edits(spark):
    """Copies with four edits in 250 words (about 0.85 of five-word shingles in common) go; other documents of the same words stay."""
    rng = np.random.default_rng(8)
    p = 1 / np.arange(1, 2001)
    texts = []
    for _ in range(60):
        words = [f"w{i}" for i in rng.choice(2000, 250, p=p / p.sum())]
        texts.append(" ".join(words))
        for at in rng.choice(250, 4, replace=False):
            words[at] = f"new{rng.integers(1000)}"
        texts.append(" ".join(words))
    kept = {r.doc_id for r in simhash.dedup(docs(spark, [(i, t, "s") for i, t in enumerate(texts)])).collect()}
    assert set(range(0, 120, 2)) <= kept and len(kept) <= 60 + 12


#: Copies at 0.8 or more that no key of the test below finds.
MISSED = 12


def plain_shingles(text):
    words = WORD.findall((text or "").lower())
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def plain_kept(texts):
    """Ids that stay by ascending id, each set compared with all kept ones."""
    sets, kept = {i: plain_shingles(t) for i, t in enumerate(texts)}, []
    for i, s in sets.items():
        if not any(s == sets[j] or len(s & sets[j]) >= 0.8 * len(s | sets[j]) for j in kept):
            kept.append(i)
    return set(kept)


def test_parity_bound_loses_no_pair():
    """No pair of sets at 0.8 or more fails the bound; most pairs far below do."""
    rng = np.random.default_rng(5)
    passed = failed = 0
    for n in (1, 2, 9, 40, 150, 600, 3000):
        for share in (0.0, 0.02, 0.05, 0.1, 0.111, 0.12, 0.2, 0.4):
            for _ in range(6):
                a = rng.integers(0, 1 << 62, n).astype(np.uint64)
                b = np.concatenate([a[int(share * n) :], rng.integers(0, 1 << 62, int(share * n * rng.random())).astype(np.uint64)])
                a, b = np.unique(a), np.unique(b)
                differ = sum(int(x).bit_count() for x in (simhash.parity_bits(a) ^ simhash.parity_bits(b)).view(np.uint64))
                assert differ <= len(a) + len(b) - 2 * len(np.intersect1d(a, b))
                may = differ * 1.8 <= (len(a) + len(b)) * 0.2 + 1e-6
                assert may or simhash.jaccard(a, b) < 0.8
                passed, failed = passed + may, failed + (not may)
    assert failed > 30 and passed > 80


def edited(words, at, rng):
    out = list(words)
    for i in at:
        out[i] = f"new{rng.integers(1 << 30)}"
    return out


@pytest.mark.parametrize("leaders", [4, 1])
def test_dedup_verifies_every_drop(spark, monkeypatch, leaders):
    """Texts with 1 to 9 edits of 250 words, chains of edits and a group of near copies: none goes without a kept text at 0.8 or more."""
    monkeypatch.setattr(simhash, "LEADERS", leaders)
    rng = np.random.default_rng(4)
    texts = ["", None, "one two", "one two three", "ONE two"]
    for n in range(40):
        words = [f"w{i}" for i in rng.integers(0, 5000, 250)]
        texts += [" ".join(words), " ".join(edited(words, rng.choice(250, 1 + n % 9, replace=False), rng))]
    words = [f"v{i}" for i in range(250)]
    for step in range(8):
        texts.append(" ".join(words))
        words = edited(words, range(step * 15, step * 15 + 15), rng)
    base = [f"u{i}" for i in rng.integers(0, 5000, 250)]
    texts += [" ".join(edited(base, rng.choice(250, 3, replace=False), rng)) for _ in range(40)]
    rows = simhash.wide_components(docs(spark, [(i, t, "s") for i, t in enumerate(texts)])).collect()
    kept = {r.doc_id for r in rows if r.doc_id == r.component_id}
    sets = [plain_shingles(t) for t in texts]
    for r in rows:
        a, b = sets[r.doc_id], sets[r.component_id]
        assert r.component_id in kept and (a == b or len(a & b) >= 0.8 * len(a | b))
    assert len(rows) == len(texts) and len(kept - plain_kept(texts)) <= MISSED and kept >= {0, 2, 3}


def test_dedup_of_inserted_and_cut_passages(spark):
    """Copies with 5 to 20 % inserted or cut in one place, and short texts that differ in the last word, all go at 0.8 or more."""
    rng = np.random.default_rng(6)
    texts = []
    for n in range(120):
        words = [f"w{i}" for i in rng.integers(0, 20000, 300)]
        k, at = (15, 30, 45, 55)[n % 4], rng.integers(0, 240)
        passage = [f"p{i}" for i in rng.integers(0, 20000, k)]
        texts += [" ".join(words), " ".join(words[:at] + passage + words[at:] if n % 2 else words[:at] + words[at + k :])]
        short = [f"s{i}" for i in rng.integers(0, 20000, 20)]
        texts += [" ".join(short), " ".join([*short[:-1], "other"])]
    kept = {r.doc_id for r in simhash.dedup(docs(spark, [(i, t, "s") for i, t in enumerate(texts)])).collect()}
    assert kept == plain_kept(texts) and len(kept) < 0.6 * len(texts)


def test_dedup_keeps_other_texts_of_an_id(spark):
    rows = [(5, "a b c d e f", "s"), (5, "quite another text of this id", "s"), (5, "A b c d e f", "s"), (6, "a b c d e f", "s"), (6, "third text with the same id six", "s")]
    got = sorted((r.doc_id, r.text.lower()) for r in simhash.dedup(docs(spark, rows)).collect())
    assert got == [(5, "a b c d e f"), (5, "quite another text of this id"), (6, "third text with the same id six")]


# ---- packages

def packed(records, force=True):
    out = io.BytesIO()
    w = warc.PackageWriter(out, force)
    for i, r in enumerate(records):
        w.add(str(i), "response", r)
    w.close()
    return out.getvalue()


def reader(data):
    return warc.PackageReader(lambda n, at: data[at : at + n], len(data))


@pytest.mark.parametrize("force", [True, False])
def test_round_trip(force):
    payloads = [b"", b"x" * 5000, "é\r\n\r\nWARC/1.1".encode(), bytes(range(256)) * 9]
    data = packed([warc.record_bytes(i, f"http://h/{i}\r\nEvil: 1", p) for i, p in enumerate(payloads)], force)
    assert zipfile.ZipFile(io.BytesIO(data)).testzip() is None
    r = reader(data)
    got = [warc.parse_record(data[at : at + n]) for at, n in r.index()]
    assert [g.payload for g in got] == payloads and [g.record_id for g in got] == ["0", "1", "2", "3"]
    assert [g.payload_digest for g in got] == [hashlib.sha1(p).hexdigest() for p in payloads]


def test_zip64_and_comments():
    data = packed([warc.record_bytes(1, "u", b"abc")])
    r = reader(data)
    entries, at = [], data.rfind(warc.END)
    start = int.from_bytes(data[at + 16 : at + 20], "little")
    size = int.from_bytes(data[at + 12 : at + 16], "little")
    end64 = warc.END64 + (44).to_bytes(8, "little") + b"-\0-\0" + b"\0" * 8 + (2).to_bytes(8, "little") * 2 + size.to_bytes(8, "little") + start.to_bytes(8, "little")
    locator = warc.LOCATOR64 + b"\0" * 4 + at.to_bytes(8, "little") + (1).to_bytes(4, "little")
    comment = b"x" + warc.END + b"y" * 40
    end = warc.END + b"\0" * 4 + b"\xff" * 12 + len(comment).to_bytes(2, "little") + comment
    wide = reader(data[:at] + end64 + locator + end)
    assert wide.members.keys() == r.members.keys() and wide.index() == r.index()
    assert not entries


def test_broken_packages():
    for bad in (b"", b"PK", b"\0" * 100):
        with pytest.raises(ValueError):
            reader(bad)
    out = io.BytesIO()
    with zipfile.ZipFile(out, "w", zipfile.ZIP_DEFLATED) as z:
        z.writestr(warc.INDEX, "a" * 1000)
    with pytest.raises(ValueError):
        reader(out.getvalue()).index()
    raw = warc.gzip.compress(warc.gzip.decompress(warc.record_bytes(1, "u", b"abc")).replace(b"\r\n\r\nabc", b"\r\n\r\nabd"))
    with pytest.raises(ValueError):
        warc.parse_record(raw)


def test_archive_query_equals_sql(spark, small):
    cols = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    ours = sorted(map(tuple, warc.op1_warc(spark, small).select(*cols).collect()))
    assert ours == sorted(duck(small).execute(f"SELECT {', '.join(cols)} FROM ({warc.SQL})").fetchall())


def test_revisits(spark, tmp_path):
    big = "é" * 600
    rows = [(1, "u", big, 0), (7, "u", big, 0), (3, None, big, 0), (None, "u", big, 0), (4, "u", "small", 0), (5, "u", "small", 0), (6, "u", None, 0), (7, "v", big, 0)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, n int")
    got = warc.read_packages(warc.write_packages(pages, f"file://{tmp_path}/a", package_bytes=300)).collect()
    assert len(got) == 8
    by = sorted((r.page_id if r.page_id is not None else -1, r.record_type, r.refers_to, r.payload_bytes) for r in got)
    assert by == [(-1, "revisit", 7, 1200), (1, "revisit", 7, 1200), (3, "revisit", 7, 1200), (4, "response", None, 5), (5, "response", None, 5), (6, "response", None, 0), (7, "response", None, 1200), (7, "response", None, 1200)]
    assert {r.html for r in got} == {big, "small", "", None} and len({r.path for r in got}) >= 2
    assert warc.read_packages(warc.write_packages(pages.limit(0), f"file://{tmp_path}/b")).count() == 0
