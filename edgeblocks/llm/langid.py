"""Language of texts and of the spans inside them: script ranges narrow the candidates, Viterbi labels the words.

A word is a run of letters in lower case. Its score under a language is the log probability of its letters, each with its two
neighbours, from counts over all labelled documents. The script of a word's first letter rules out languages that hardly
ever use it. Along the words of a text the best sequence of languages is found, where each change costs SWITCH; runs of one
language are the spans, and the language with most letters is the text's.

Defined cases: null text, or one with no letter, is "und" with score 0; documents of null lang are not learnt from; a null id is
never held out; without any learnt language all texts are "und"; ties go to the language that is first in order; a word in a
script that no language uses scores alike under all; repeated rows and extra columns do no harm.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .bpe import by_size

#: Buckets of letter contexts, cost of a change in log units, least share of a language's letters for a script of its own.
BUCKETS, SWITCH, SCRIPT_SHARE = 1 << 16, 12.0, 0.01
#: First code points of script ranges (Unicode blocks); each range goes up to the next.
SCRIPTS = [
    (0x0000, "latin"), (0x0370, "greek"), (0x0400, "cyrillic"), (0x0530, "armenian"), (0x0590, "hebrew"), (0x0600, "arabic"),
    (0x0700, "syriac"), (0x0750, "arabic"), (0x0780, "thaana"), (0x0900, "devanagari"), (0x0980, "bengali"), (0x0A00, "gurmukhi"),
    (0x0A80, "gujarati"), (0x0B00, "oriya"), (0x0B80, "tamil"), (0x0C00, "telugu"), (0x0C80, "kannada"), (0x0D00, "malayalam"),
    (0x0D80, "sinhala"), (0x0E00, "thai"), (0x0E80, "lao"), (0x0F00, "tibetan"), (0x1000, "myanmar"), (0x10A0, "georgian"),
    (0x1100, "hangul"), (0x1200, "ethiopic"), (0x13A0, "other"), (0x1780, "khmer"), (0x1800, "mongolian"), (0x1900, "other"),
    (0x1E00, "latin"), (0x1F00, "greek"), (0x2000, "other"), (0x3040, "kana"), (0x3100, "other"), (0x3130, "hangul"),
    (0x3190, "other"), (0x3400, "han"), (0xA000, "other"), (0xAC00, "hangul"), (0xD7B0, "other"), (0xF900, "han"), (0xFB00, "other"),
    (0x20000, "han"), (0x32000, "other"),
]
_STARTS = np.array([s for s, _ in SCRIPTS], np.uint32)
NAMES = sorted({n for _, n in SCRIPTS})
_SCRIPT = np.array([NAMES.index(n) for _, n in SCRIPTS])


#: Numbers of languages: 32 767 at most.
LABEL = np.int16


@cache
def _letters() -> np.ndarray:
    return np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)


@dataclass
class Words:
    """The words of some texts: bucket of each letter, and per word its first letter, start, length, script and text."""

    buckets: np.ndarray
    starts: np.ndarray
    lengths: np.ndarray
    scripts: np.ndarray
    begins: np.ndarray
    per_text: np.ndarray


def words_of(texts: list[str | None]) -> Words:
    low = [(t or "").lower() for t in texts]
    cps = np.frombuffer(" ".join(["", *low, ""]).encode("utf-32-le", "surrogatepass"), np.uint32)
    alpha = _letters()[cps]
    c = np.where(alpha, cps, 32).astype(np.uint32)
    at = np.flatnonzero(alpha)
    mixed = c[at - 1] * np.uint32(0x9E3779B1) ^ c[at] * np.uint32(0x85EBCA6B) ^ c[at + 1] * np.uint32(0xC2B2AE35) if at.size else np.zeros(0, np.uint32)
    first = np.flatnonzero(~alpha[at - 1]) if at.size else np.zeros(0, np.int64)
    begins = at[first]
    lengths = np.diff(np.append(first, at.size))
    scripts = _SCRIPT[np.searchsorted(_STARTS, c[begins], side="right") - 1]
    ends = np.cumsum([len(t) + 1 for t in low])
    per_text = np.diff(np.searchsorted(begins, np.concatenate([[0], ends]), side="right"))
    mixed = (mixed ^ mixed >> np.uint32(15)) * np.uint32(0x2C1B3C6D)
    return Words((mixed >> np.uint32(16)).astype(np.int64) % BUCKETS, first, lengths, scripts, begins, per_text)


@dataclass
class Model:
    langs: list[str]
    scores: np.ndarray  # language, bucket
    scripts: np.ndarray  # script, language: may be

    def emissions(self, w: Words) -> np.ndarray:
        """Log score of each word under each language, where its script allows it."""
        out = np.empty((len(w.starts), len(self.langs)), np.float32)
        for i, table in enumerate(self.scores):
            out[:, i] = np.add.reduceat(table[w.buckets], w.starts) if len(w.starts) else 0
        allowed = self.scripts[w.scripts]
        none = ~allowed.any(axis=1)
        out[~allowed] = -1e4
        out[none] = 0
        return out


def viterbi(e: np.ndarray, per_text: np.ndarray, switch: float = SWITCH) -> np.ndarray:
    """Best label of each word, texts in lockstep: at step t, all texts that are longer than t."""
    n_lang = e.shape[1]
    order = np.argsort(-per_text, kind="stable")
    lengths = per_text[order]
    starts = (np.cumsum(per_text) - per_text)[order]
    labels = np.zeros(len(e), LABEL)
    steps = int(lengths[0]) if len(lengths) else 0
    if not steps or n_lang == 1:
        return labels
    active = len(lengths) - np.searchsorted(lengths[::-1], np.arange(steps), side="right")
    own, back = np.arange(n_lang, dtype=LABEL)[None, :], []
    v = np.zeros((active[0], n_lang), np.float32)
    last = np.zeros(len(lengths), np.int64)
    for t in range(steps):
        n = active[t]
        if n < len(v):
            last[n : len(v)] = v[n:].argmax(axis=1)
            v = v[:n]
        lead = v.argmax(axis=1)
        top = v[np.arange(n), lead][:, None] - np.float32(switch)
        back.append(np.where(v >= top, own, lead[:, None].astype(LABEL)))
        v = np.maximum(v, top) + e[starts[:n] + t]
        v -= v.max(axis=1, keepdims=True)
    last[: len(v)] = v.argmax(axis=1)
    for t in range(steps - 1, -1, -1):
        n = active[t]
        labels[starts[:n] + t] = last[:n]
        last[:n] = back[t][np.arange(n), last[:n]]
    return labels


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(F.encode(doc_id.cast("string"), "utf-8")) % 3 == 1, F.lit(False))


def fit(docs: DataFrame) -> Model:
    """Counts over all documents with lang. The driver receives at most (languages x (BUCKETS + scripts)) sums."""

    def count(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for b in it:
            for part in by_size(b):
                langs, texts = part.column("lang").to_pylist(), part.column("text").to_pylist()
                for lang in set(langs):
                    w = words_of([t for t, x in zip(texts, langs) if x == lang])
                    have = sums.setdefault(lang, np.zeros(BUCKETS + len(NAMES), np.int64))
                    have[:BUCKETS] += np.bincount(w.buckets, minlength=BUCKETS)
                    have[BUCKETS:] += np.bincount(w.scripts, weights=w.lengths, minlength=len(NAMES)).astype(np.int64)
        for lang, have in sums.items():
            at = np.flatnonzero(have)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at, pa.int64()), pa.array(have[at], pa.int64())], names=["lang", "at", "n"])

    rows = docs.where("lang IS NOT NULL AND text IS NOT NULL").select("lang", F.col("text").cast("string").alias("text"))
    sums = rows.mapInArrow(count, "lang string, at bigint, n bigint").groupBy("lang", "at").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(sums["lang"].unique())
    table = np.zeros((len(langs), BUCKETS + len(NAMES)))
    for i, lang in enumerate(langs):
        own = sums[sums["lang"] == lang]
        table[i, own["at"].to_numpy()] = own["n"].to_numpy()
    grams, scripts = table[:, :BUCKETS] + 0.1, table[:, BUCKETS:]
    share = scripts / np.maximum(scripts.sum(axis=1, keepdims=True), 1)
    return Model(langs, np.log(grams / grams.sum(axis=1, keepdims=True)).astype(np.float32), (share >= SCRIPT_SHARE).T.copy())


def predict(docs: DataFrame, model: Model, keep_spans: bool = False) -> DataFrame:
    """doc_id, lang_pred, score (share of letters in lang_pred), and with keep_spans the (start, lang) of each span in code points
    of the lower-cased text."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema["doc_id"].dataType.simpleString()

    def label(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for b in it:
            for part in by_size(b, 2 << 20):
                w = words_of(part.column("text").to_pylist())
                n = part.num_rows
                text_of = np.repeat(np.arange(n), w.per_text)
                if m.langs:
                    labels = viterbi(m.emissions(w), w.per_text)
                    mass = np.bincount(text_of * len(m.langs) + labels, weights=w.lengths, minlength=n * len(m.langs)).reshape(n, -1)
                else:
                    labels, mass = np.zeros(len(w.starts), LABEL), np.zeros((n, 1))
                total = mass.sum(axis=1)
                best = mass.argmax(axis=1)
                lang = [m.langs[i] if t else "und" for i, t in zip(best, total)]
                score = mass[np.arange(n), best] / np.maximum(total, 1)
                cols, names = [part.column("doc_id"), pa.array(lang, pa.string()), pa.array(score, pa.float64())], ["doc_id", "lang_pred", "score"]
                if keep_spans:
                    new = np.flatnonzero(np.diff(text_of, prepend=-1) | (np.diff(labels, prepend=-1) != 0))
                    base = np.cumsum([0, *(len((t or "").lower()) + 1 for t in part.column("text").to_pylist())]) + 1
                    spans = [[] for _ in range(n)]
                    for i in new if m.langs else []:
                        spans[text_of[i]].append({"start": int(w.begins[i] - base[text_of[i]]), "lang": m.langs[labels[i]]})
                    cols, names = [*cols, pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("lang", pa.string())])))], [*names, "spans"]
                yield pa.RecordBatch.from_arrays(cols, names=names)

    schema = f"doc_id {kind}, lang_pred string, score double" + ", spans array<struct<start:bigint,lang:string>>" * keep_spans
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(label, schema)


def op5_langid(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(docs.where(~held_out(F.col("doc_id"))))
    return predict(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
