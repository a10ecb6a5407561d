"""Toxicity by a classifier chain of linear models.

Categories are predicted in order; each later model also sees the earlier categories' log-odds. In training those come
out of fold, from models that did not see the document, as they will be at prediction time. Features are the words of the
whole text (presence, hashed to BUCKETS) of which each model keeps the most telling ones, and three measures of the text.
The chain is fitted on at most SAMPLE labelled documents, half of them of the last category, chosen by hash of the id; all
documents are scored. The cut of the last category is the one of best out-of-fold F1 at the labels' own rates.

Defined cases: null text and text without words have probability 0 and are not toxic; labels that repeat a document count once,
with the larger value; documents without label are scored like all others; a category whose labels are all of one class gets that
class for every document with words, and the rest of the chain is fitted as ever; with no labels, or with a last category of one class,
nothing is toxic; extra columns and repeated rows do no harm; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import by_size
from .columns import unused
from .plain import PLAIN

#: Labelled documents for the fit, word buckets, words that a model keeps, folds.
SAMPLE, BUCKETS, KEPT, FOLDS = 6000, 1 << 20, 1024, 5
#: The chain: category and the condition on a label row.
CHAIN = [("low_quality", "quality = 0"), ("toxic", "toxic = 1")]
MEASURES = 3
#: Bytes of the word beginnings that count as words too, for inflected forms.
STEMS = (4, 6)


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Different buckets of words and word beginnings, sorted, and the measures: log count of words, share of different ones, share of symbols."""
    raw = (text or "").lower().encode("utf-8", "surrogatepass")
    plain = raw.translate(PLAIN)
    words = plain.split()
    if not words:
        return np.zeros(0, np.int32), np.zeros(MEASURES)
    different = set(words)
    marks = different.union(*({w[:n] + b"~" for w in different if len(w) > n} for n in STEMS))
    ids = np.unique(np.fromiter(map(zlib.crc32, marks), np.uint32, len(marks)) % BUCKETS).astype(np.int32)
    symbols = plain.count(b" ") - sum(map(raw.count, (b" ", b"\n", b"\t", b"\r")))
    return ids, np.array([np.log1p(len(words)) / 10, len(different) / len(words), symbols / len(raw)])


@dataclass
class Linear:
    """Logistic regression on chosen words, measures and earlier log-odds."""

    words: np.ndarray
    weights: np.ndarray
    bias: float

    @property
    def constant(self) -> bool:
        """Whether the category had one class only, so that its log-odds tell later models nothing."""
        return not self.weights.any()

    def logit(self, ids: np.ndarray, dense: np.ndarray) -> float:
        at = np.searchsorted(self.words, ids)
        at = at[(at < len(self.words)) & (self.words[np.minimum(at, len(self.words) - 1)] == ids)] if len(self.words) else at[:0]
        n = len(self.words)
        return float(self.weights[at].sum() + self.weights[n:] @ dense + self.bias)


def _fit_linear(docs: list[np.ndarray], dense: np.ndarray, y: np.ndarray, kept: int, penalty: float = 1.0, rounds: int = 150) -> Linear:
    """The kept words of largest two-sample z, then accelerated gradient steps on the penalised log loss."""
    flat = np.concatenate([np.zeros(0, np.int32), *docs])
    owner = np.repeat(np.arange(len(docs)), [len(d) for d in docs])
    ids, at, counts = np.unique(flat, return_inverse=True, return_counts=True)
    pos = np.bincount(at, weights=y[owner], minlength=len(ids))
    p1, p0, p = (pos + 0.5) / (y.sum() + 1), (counts - pos + 0.5) / (len(y) - y.sum() + 1), (counts + 1) / (len(y) + 2)
    z = np.abs(p1 - p0) / np.sqrt(p * (1 - p) * (1 / max(y.sum(), 1) + 1 / max(len(y) - y.sum(), 1)))
    z[counts < 3] = 0
    best = np.sort(np.argsort(-z, kind="stable")[:kept])
    best = best[z[best] > 0]
    x = np.zeros((len(docs), len(best) + dense.shape[1] + 1), np.float32)
    column = np.full(len(ids), -1)
    column[best] = np.arange(len(best))
    hit = column[at] >= 0
    x[owner[hit], column[at][hit]] = 1
    x[:, len(best) : -1], x[:, -1] = dense, 1
    v = np.ones(x.shape[1], np.float32)
    for _ in range(20):
        v = x.T @ (x @ v)
        v /= np.linalg.norm(v)
    step = 1 / (0.26 * float(v @ (x.T @ (x @ v))) + penalty)
    w, ahead, t = np.zeros(x.shape[1], np.float32), np.zeros(x.shape[1], np.float32), 1.0
    ridge, step, y = np.full(x.shape[1], penalty, np.float32), np.float32(step), y.astype(np.float32)
    ridge[-1] = 0
    for _ in range(rounds):
        grad = x.T @ (1 / (1 + np.exp(-np.clip(x @ ahead, -30, 30))) - y) + ridge * ahead
        new, t2 = ahead - step * grad, (1 + np.sqrt(1 + 4 * t * t)) / 2
        ahead, w, t = new + np.float32((t - 1) / t2) * (new - w), new, t2
    return Linear(ids[best], w[:-1].astype(float), float(w[-1]))


@dataclass
class Chain:
    names: list[str]
    models: list[Linear] = field(default_factory=list)
    cut: float = 0.5

    def probabilities(self, text: str | None) -> list[float]:
        ids, dense = features(text)
        if not len(ids) or not self.models:
            return [0.0] * len(self.names)
        out: list[float] = []
        seen: list[float] = []
        for model in self.models:
            out.append(float(np.clip(model.logit(ids, np.concatenate([dense, seen])), -30, 30)))
            seen.append(0.0 if model.constant else out[-1])
        return [1 / (1 + np.exp(-z)) for z in out]


def fit_chain(docs: list[np.ndarray], dense: np.ndarray, labels: np.ndarray, names: list[str], rates: float | None = None, kept: int = KEPT, folds: int = FOLDS) -> Chain:
    """labels: documents x categories in chain order. rates: the last category's share among all labels."""
    chain = Chain(names)
    if not len(docs) or (labels.min(axis=0) == labels.max(axis=0)).all():
        return chain
    fold = np.arange(len(docs)) % folds
    for c in range(labels.shape[1]):
        y = labels[:, c].astype(float)
        if y.min() == y.max():  # nothing to tell apart: a constant for all
            out = np.full(len(docs), 30.0 if y[0] else -30.0)
            chain.models.append(Linear(np.zeros(0, np.int32), np.zeros(dense.shape[1]), out[0]))
            dense = np.hstack([dense, np.zeros((len(docs), 1))])
            continue
        out = np.zeros(len(docs))
        for f in range(folds):
            rest, own = np.flatnonzero(fold != f), np.flatnonzero(fold == f)
            model = _fit_linear([docs[i] for i in rest], dense[rest], y[rest], kept)
            out[own] = [np.clip(model.logit(docs[i], dense[i]), -30, 30) for i in own]
        chain.models.append(_fit_linear(docs, dense, y, kept))
        dense = np.hstack([dense, out[:, None]])
    if y.min() == y.max():
        chain.cut = 1.0
        return chain
    order = np.argsort(-out)
    share = y.mean()
    rate = share if rates is None else rates
    w = np.where(y == 1, rate / share, (1 - rate) / (1 - share))[order]
    hit, all_ = np.cumsum(w * y[order]), np.cumsum(w)
    f1 = 2 * hit / (all_ + (w * y[order]).sum())
    k = int(f1.argmax())
    edge = (out[order][k] + out[order][min(k + 1, len(order) - 1)]) / 2
    chain.cut = float(1 / (1 + np.exp(-edge)))
    return chain


def fit(docs: DataFrame, labels: DataFrame, chain: list[tuple[str, str]] = CHAIN, sample: int = SAMPLE) -> Chain:
    """Draws the sample (ids by hash, half of the last category) and fits on the driver. Features come from the executors."""
    names = [n for n, _ in chain]
    flags = labels.where("doc_id IS NOT NULL").groupBy("doc_id").agg(*(F.max(F.coalesce(F.expr(e).cast("int"), F.lit(0))).alias(n) for n, e in chain))
    shares = flags.agg(F.avg(names[-1])).first()[0]
    part = [flags.where(F.col(names[-1]) == v).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample // 2) for v in (0, 1)]
    kind = docs.schema["doc_id"].dataType.simpleString()
    picked = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(part[0].union(part[1])), "doc_id")

    def read(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for p in by_size(b):
                got = [features(t) for t in p.column("text").to_pylist()]
                yield pa.RecordBatch.from_arrays([p.column("doc_id"), *(p.column(n) for n in names), pa.array([g[0] for g in got], pa.list_(pa.int32())), pa.array([g[1] for g in got], pa.list_(pa.float64()))], names=["doc_id", *names, "ids", "dense"])

    rows = picked.mapInArrow(read, f"doc_id {kind}, {', '.join(f'{n} int' for n in names)}, ids array<int>, dense array<double>").dropDuplicates(["doc_id"]).toArrow()
    order = np.argsort(rows.column("doc_id").to_numpy(), kind="stable")
    rows = rows.combine_chunks()
    flat = lambda c: rows.column(c).combine_chunks() if rows.num_rows else None
    ids, dense = ([], []) if not rows.num_rows else (np.split(flat("ids").flatten().to_numpy(), np.cumsum(flat("ids").value_lengths().to_numpy())[:-1]), flat("dense").flatten().to_numpy().reshape(-1, MEASURES))
    table = np.stack([rows.column(n).to_numpy() for n in names], axis=1)[order] if rows.num_rows else np.zeros((0, len(names)))
    return fit_chain([ids[i] for i in order], np.array([dense[i] for i in order]).reshape(len(order), MEASURES), table, names, shares)


def predict(docs: DataFrame, chain: Chain, keep: bool = False) -> DataFrame:
    """doc_id, p_<category> of each, toxic (the last above its cut); with keep, the columns of docs and the flag under a name of its own, last."""
    sent = docs.sparkSession.sparkContext.broadcast(chain)
    (flag_name,) = unused(docs, "toxic")

    def score(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = sent.value
        for b in it:
            for p in by_size(b):
                got = [c.probabilities(t) for t in p.column("text").to_pylist()]
                flag = pa.array([g[-1] > c.cut and g[-1] > 0 for g in got], pa.bool_())
                if keep:
                    yield pa.RecordBatch.from_arrays([*p.columns, flag], names=[*p.schema.names, flag_name])
                else:
                    yield pa.RecordBatch.from_arrays([p.column("doc_id"), *(pa.array([g[i] for g in got], pa.float64()) for i in range(len(c.names))), flag], names=["doc_id", *(f"p_{n}" for n in c.names), "toxic"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    if keep:
        fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
        return docs.mapInArrow(score, f"{fields}, `{flag_name}` boolean")
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(score, f"doc_id {kind}, {', '.join(f'p_{n} double' for n in chain.names)}, toxic boolean")


def reject(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """docs without those that the chain calls toxic."""
    scored = predict(docs, fit(docs, labels, **options), keep=True)
    return scored.where(~F.col(scored.columns[-1])).select(*docs.columns)


def op6_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return predict(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
