"""BPE encoding with a minimal acyclic transducer for frequent words, and decoding.

Frequent words of the corpus are encoded once and compiled into an automaton that shares prefixes and suffixes. The sum of the
outputs on a word's path is its number in the list, which gives its ids. Workers map the automaton's file into memory and look up
the new words of a batch together, one byte position at a time; a word that it lacks is merged exactly. Results are those of the
tokenizer file with no special tokens added, truncated or padded; texts with letters outside the scripts of RANGE are cut into
words by the tokenizers library itself, since Unicode tables differ between versions.

Defined cases: null text is empty (no ids); the tokenizer's special strings inside a text become their ids; very long words are
merged with a heap; repeated rows and extra columns do no harm; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import mmap
import os
import re
import tempfile
import unicodedata
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import materialise

#: Words of the lexicon, and words that a worker remembers beside it before it starts anew.
LEXICON, REMEMBERED = 50_000, 500_000
#: Texts below this code point are cut into words here.
RANGE = "԰"
#: Fixed value: the tokenizer's word pattern, with its white space spelt out up to RANGE.
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\t-\r \x85\xA0\p{L}\p{N}]+"

#: The same for texts in the first 256 code points, with their letters and numbers spelt out.
_LETTERS, _NUMBERS = "a-zA-Zªµº\xc0-\xd6\xd8-\xf6\xf8-\xff", "0-9²³¹¼½¾"
LATIN_WORDS = re.compile(f"[{_LETTERS}]+|'(?:s|t|re|ve|m|ll|d)|[{_NUMBERS}]|[^\\t-\\r \\x85\\xA0{_LETTERS}{_NUMBERS}]+").findall


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in a byte-level vocabulary."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class Automaton:
    """Minimal acyclic automaton over byte strings whose path outputs add up to a word's rank in sorted order."""

    def __init__(self, keys: np.ndarray, targets: np.ndarray, outputs: np.ndarray, final: np.ndarray):
        self.keys, self.targets, self.outputs, self.final = keys, targets, outputs, final

    @classmethod
    def build(cls, words: Iterable[bytes]) -> Automaton:
        """words: sorted and different. States are shared as soon as no later word can change them."""
        known: dict[tuple, int] = {}
        counts: list[int] = []  # words below each finished state
        shape: list[tuple] = []

        def finish(node: list) -> int:
            final, arcs = node
            form = (final, tuple(arcs))
            if form not in known:
                known[form] = len(shape)
                shape.append(form)
                counts.append(final + sum(counts[t] for _, t in arcs))
            return known[form]

        path: list[list] = [[0, []]]  # of the last word: final, finished arcs
        last = b""

        def close(depth: int) -> None:
            while len(path) - 1 > depth:
                done = finish(path.pop())
                path[-1][1].append((last[len(path) - 1], done))

        for word in words:
            same = next((i for i, (a, b) in enumerate(zip(last, word)) if a != b), min(len(last), len(word)))
            close(same)
            path.extend([0, []] for _ in word[same:])
            path[-1][0], last = 1, word
        close(0)
        root = finish(path[0])
        keys, targets, outputs = [], [], []
        for state, (final, arcs) in enumerate(shape):
            skipped = final
            for label, target in arcs:
                keys.append((root - state) * 256 + label)  # the root becomes state 0
                targets.append(root - target)
                outputs.append(skipped)
                skipped += counts[target]
        order = np.argsort(np.array(keys, np.int64), kind="stable")
        final = np.array([f for f, _ in reversed(shape)], np.int8)
        pick = lambda x, kind: np.array(x, kind)[order] if keys else np.zeros(0, kind)
        return cls(pick(keys, np.int64), pick(targets, np.int32), pick(outputs, np.int32), final)

    def ranks(self, words: list[bytes]) -> np.ndarray:
        """The rank of each word, -1 for those that are not in the automaton; all words advance together."""
        lengths = np.fromiter(map(len, words), np.int64, len(words))
        flat = np.frombuffer(b"".join(words), np.uint8)
        starts = np.cumsum(lengths) - lengths
        state, total = np.zeros(len(words), np.int64), np.zeros(len(words), np.int64)
        live, at = np.arange(len(words)), 0
        while live.size:
            ended = lengths[live] == at
            done = live[ended]
            total[done] = np.where(self.final[state[done]] == 1, total[done], -1)
            live = live[~ended]
            if not live.size:
                break
            key = state[live] * 256 + flat[starts[live] + at]
            arc = np.searchsorted(self.keys, key)
            there = arc < len(self.keys)
            there[there] = self.keys[arc[there]] == key[there]
            total[live[~there]] = -1
            live, arc = live[there], arc[there]
            total[live] += self.outputs[arc]
            state[live] = self.targets[arc]
            at += 1
        return total



def pack(parts: list[np.ndarray]) -> bytes:
    """Arrays one after the other, each on an eight-byte boundary, behind a table of their kinds and lengths."""
    head = json.dumps([[str(x.dtype), len(x)] for x in parts]).encode()
    blocks = [len(head).to_bytes(8, "little"), head, *(np.ascontiguousarray(x).tobytes() for x in parts)]
    return b"".join(x + b"\0" * (-len(x) % 8) for x in blocks)


def unpack(data) -> list[np.ndarray]:
    n = int.from_bytes(data[:8], "little")
    at, out = 8 + n + -n % 8, []
    for kind, length in json.loads(bytes(data[8 : 8 + n])):
        out.append(np.frombuffer(data, kind, length, at))
        at += out[-1].nbytes + -out[-1].nbytes % 8
    return out


#: Layout of a merge: rank above _BITS bits of id; _NONE sorts after all of them.
_BITS = 24
_ID, _NONE = (1 << _BITS) - 1, 1 << 62


class Merger:
    """Exact byte-pair merges of single words by the ranks of a tokenizer file."""

    def __init__(self, spec: dict):
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix = model.get("end_of_word_suffix") or ""
        merges = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        #: pair of ids to rank and the id of what they become, in one number that sorts by rank
        self.ranks = {(self.vocab[a], self.vocab[b]): i << _BITS | self.vocab[a + b] for i, (a, b) in enumerate(merges)}
        letters = byte_letters()
        self.inner = [self.vocab[x] for x in letters]
        self.ending = [self.vocab[x + self.suffix] for x in letters]

    def merge(self, word: bytes) -> list[int]:
        if not word:
            return []
        ids = [self.inner[b] for b in word[:-1]] + [self.ending[word[-1]]]
        if len(ids) > 64:
            return self._merge_long(ids)
        get = self.ranks.get
        pairs = [get(p, _NONE) for p in zip(ids, ids[1:])]
        while pairs:
            best = min(pairs)
            if best == _NONE:
                break
            i = pairs.index(best)
            ids[i] = new = best & _ID
            del ids[i + 1], pairs[i]
            if i < len(pairs):
                pairs[i] = get((new, ids[i + 1]), _NONE)
            if i:
                pairs[i - 1] = get((ids[i - 1], new), _NONE)
        return ids

    def _merge_long(self, ids: list[int]) -> list[int]:
        """The same order of merges with a heap over a linked list."""
        n = len(ids)
        after, before = [*range(1, n + 1)], [*range(-1, n - 1)]
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := self.ranks.get((ids[i], ids[i + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            rank, i, a, b = heapq.heappop(heap)
            j = after[i] if ids[i] == a else n
            if j >= n or ids[j] != b:
                continue
            ids[i], ids[j], after[i] = rank & _ID, -1, after[j]
            if after[j] < n:
                before[after[j]] = i
            for left in (before[i], i):
                right = after[left] if left >= 0 else n
                if right < n and (r := self.ranks.get((ids[left], ids[right]))) is not None:
                    heapq.heappush(heap, (r, left, ids[left], ids[right]))
        return [x for x in ids if x >= 0]


class Encoder:
    """A worker's encoder: mapped lexicon, remembered words, exact merges for the rest.

    The lexicon came by broadcast; the file that it is mapped from is the worker's own, unlinked as soon as it is mapped, and nobody else reads it.
    """

    def __init__(self, spec_json: str, lexicon: bytes | None):
        import regex
        from tokenizers import Tokenizer

        spec = json.loads(spec_json)
        self.merger = Merger(spec)
        self.words = regex.compile(WORDS).findall
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.cut = re.compile("(" + "|".join(map(re.escape, self.special)) + ")").split if self.special else lambda t: [t]
        self.library = Tokenizer.from_str(spec_json)
        self.token = {i: t for t, i in [*self.merger.vocab.items(), *self.special.items()]}
        self.token_list = [self.token.get(i, "") for i in range(max(self.token) + 1)]
        self.known: dict[str, bytes] = {}
        self.auto = None
        if lexicon:
            file, path = tempfile.mkstemp()
            os.write(file, lexicon)
            mapped = mmap.mmap(file, 0, access=mmap.ACCESS_READ)
            os.close(file)
            os.unlink(path)  # the mapping holds it
            *auto, self.ends, self.ids = unpack(memoryview(mapped))
            self.auto = Automaton(*auto)

    def pieces(self, text: str) -> list[str]:
        """Words of a text without special strings, after NFC and lower case."""
        try:
            text.encode("latin-1")  # such text is in NFC already
            return LATIN_WORDS(text.lower())
        except UnicodeEncodeError:
            pass
        if max(text) < RANGE and max(text := unicodedata.normalize("NFC", text)) < RANGE:
            return self.words(text.replace("Σ", "σ").lower())
        back = {c: b for b, c in enumerate(byte_letters())}
        cut = self.library.pre_tokenizer.pre_tokenize_str(self.library.normalizer.normalize_str(text))
        return [bytes(back[c] for c in w).decode() for w, _ in cut]

    def learn(self, words: set[str]) -> None:
        new = words.difference(self.known)
        if len(self.known) + len(new) > REMEMBERED:
            self.known.clear()
            new = words
        if not new:
            return
        new = list(new)
        raw = [w.encode() for w in new]
        ranks = self.auto.ranks(raw) if self.auto else np.full(len(new), -1)
        for w, b, r in zip(new, raw, ranks.tolist()):
            ids = self.merger.merge(b) if r < 0 else self.ids[self.ends[r] : self.ends[r + 1]]
            self.known[w] = np.asarray(ids, "<u4").tobytes()

    def encode_all(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers; their new words are looked up together."""
        parts = [[(x, None if x in self.special else self.pieces(x)) for x in (self.cut(t) if "<|" in t else [t]) if x] for t in (t or "" for t in texts)]
        self.learn({w for t in parts for _, words in t if words for w in words})
        ids = lambda x, words: [self.special[x].to_bytes(4, "little")] if words is None else map(self.known.__getitem__, words)
        return [b"".join(b"".join(ids(x, words)) for x, words in t) for t in parts]

    def encode(self, text: str | None) -> bytes:
        return self.encode_all([text])[0]

    def decode(self, ids: bytes) -> str:
        """The tokens of the ids with a space between them: the file names no decoder."""
        return " ".join(map(self.token_list.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def by_size(batch: pa.RecordBatch, most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of a batch of about so many bytes of text, a row at least."""
    ends = np.cumsum([len(t) if t is not None else 0 for t in (x.as_buffer() if x.is_valid else None for x in batch.column("text"))])
    lo = 0
    while lo < batch.num_rows:
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + most, side="right")))
        yield batch.slice(lo, hi - lo)
        lo = hi


def frequent_words(docs: DataFrame, n: int = LEXICON) -> list[str]:
    """The most frequent letter words over all documents, n at most.

    A histogram of counts in steps of a sixteenth of a power of two says from which count on there are n words at most; the
    driver receives that histogram (some thousand rows) and those words.
    """
    words = docs.select(F.explode(F.split(F.lower(F.col("text")), r"[^\p{L}]+")).alias("word")).where("word <> ''")
    counts = words.groupBy("word").agg(F.count(F.lit(1)).alias("n")).where("n > 1 and length(word) <= 64")
    counts = materialise(counts.select("word", F.floor(F.log2("n") * 16).cast("int").alias("step")), "word-counts")
    least, total = None, 0
    for r in sorted(counts.groupBy("step").count().collect(), key=lambda r: -r["step"]):
        total += r["count"]
        if total > n:
            break
        least = r["step"]
    return [] if least is None else [r.word for r in counts.where(F.col("step") >= least).select("word").collect()]


def compile_lexicon(words: Iterable[str], spec_json: str) -> bytes:
    merger = Merger(json.loads(spec_json))
    raw = sorted({w.encode() for w in words})
    auto = Automaton.build(raw)
    ids = [merger.merge(w) for w in raw]
    ends = np.cumsum([0, *map(len, ids)]).astype(np.int32)
    flat = np.array([x for y in ids for x in y], np.int32)
    return pack([auto.keys, auto.targets, auto.outputs, auto.final, ends, flat])


def tokenizer_json(path: str | None = None) -> str:
    """The tokenizer file, read by the driver; by default the installed public word-level one."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    with open(path, encoding="utf-8") as f:
        return f.read()


def encode(docs: DataFrame, path: str | None = None, lexicon_words: int = LEXICON, keep_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, and with keep_ids also ids array<int>."""
    spark, spec = docs.sparkSession, tokenizer_json(path)
    lexicon = compile_lexicon(frequent_words(docs, lexicon_words), spec)
    shared = spark.sparkContext.broadcast((spec, lexicon))  # a few MB: the tokenizer file and lexicon_words words
    kind = docs.schema["doc_id"].dataType.simpleString()

    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = Encoder(*shared.value)
        for b in it:
            for part in by_size(b):
                n, sha, dec, ids = [], [], [], []
                for raw in enc.encode_all(part.column("text").to_pylist()):
                    text = enc.decode(raw)
                    n.append(len(raw) // 4)
                    sha.append(hashlib.sha256(raw).hexdigest())
                    dec.append(hashlib.sha256(text.encode()).hexdigest())
                    if keep_ids:
                        ids.append(np.frombuffer(raw, "<u4").astype(np.int32))
                cols = [part.column("doc_id"), pa.array(n, pa.int64()), pa.array(sha, pa.string()), pa.array(dec, pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if keep_ids:
                    cols, names = [*cols, pa.array(ids, pa.list_(pa.int32()))], [*names, "ids"]
                yield pa.RecordBatch.from_arrays(cols, names=names)

    schema = f"doc_id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * keep_ids
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(batches, schema)


def op10_bpe(spark, sf_dir: str) -> DataFrame:
    return encode(spark.read.parquet(f"{sf_dir}/documents.parquet"))
