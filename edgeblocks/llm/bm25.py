"""Exact BM25 top-k with block-max WAND pruning, per shard, merged exactly with global statistics.

Each document becomes its different terms with counts, once. Document frequencies of the queries' terms, the number of documents
and their mean length are taken over all documents, so scores do not depend on the shards. A task turns its documents into
shards of bounded postings. Inside a shard documents are ordered by their most frequent terms, so that documents of one language and kind stand
together; a shard has posting lists, the maximum of each list, and the maximum of each list in each block of BLOCK documents.

Queries of one kind go over the blocks side by side, in document order. The pivot is the next block whose block maxima together reach the
k-th best score so far of one of them; everything before it is skipped, its postings are not read. First the blocks of the largest bounds are scored, which
gives k-th best scores to begin with. The maxima of the lists that stand in many documents are a table, so the bounds of all queries are
one matrix product and the sum of what the rare lists add; a run of pivot blocks is scored likewise, from a table of the most frequent lists and the postings of
the others. These products are in single precision and only choose: a document goes on if its sum, with the rounding allowed for, reaches the k-th best
score so far, and is scored in full from its forward list at the end. The k-th best score rises after each run and carries over from shard to shard of a
task. A query is the set of its different terms: how often it repeats one has no weight.

Defined cases: null text and text without terms match nothing and ask nothing; a query matches its own document too; ties go to
the smaller id; documents of null id take no part; documents that share no term with a query are not returned, so fewer than
k may be; an empty table gives an empty result; repeated rows are documents of their own, extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import fresh_dir, materialise
from .bpe import by_size
from .memory import give_back
from .plain import PLAIN

K1, B = 1.2, 0.75
#: Documents in a block, documents and postings that fill a shard, terms of the queries in a broadcast (16 bytes each), blocks of a run.
BLOCK, SHARD, SHARD_POSTINGS, PACK_TERMS, RUN = 32, 8192, 2_000_000, 4_000_000, 64
#: Documents after which the size of a shard is looked at, queries that go over a shard side by side.
SLICE, GROUP = 512, 64
#: A list is a column of the shard's table of documents (of blocks) if it holds one in so many documents, up to so many columns.
DOC_SHARE, DOC_COLUMNS, BLOCK_SHARE, BLOCK_COLUMNS = 32, 1024, 256, 4096
#: Relative error allowed to sums in single precision: at most BLOCK_COLUMNS + 2 roundings of 2**-24 each, since nothing is negative.
SLACK = 1e-3


def terms_of(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the different terms, sorted, and their counts. A term is a run of ASCII letters and digits and other bytes."""
    from xxhash import xxh64_intdigest

    counts = Counter((text or "").lower().encode("utf-8", "surrogatepass").translate(PLAIN).split())
    hashes = np.fromiter(map(xxh64_intdigest, counts), np.uint64, len(counts)).view(np.int64)
    order = np.argsort(hashes)
    return hashes[order], np.fromiter(counts.values(), np.int32, len(counts))[order]


def forward_index(docs: DataFrame) -> DataFrame:
    """doc_id, terms, counts, length and how many different terms (width) for every document with an id."""

    def read(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for p in by_size(b):
                got = [terms_of(t) for t in p.column("text").to_pylist()]
                ends = np.cumsum([0, *(len(t) for t, _ in got)]).astype(np.int32)
                flat = [np.concatenate([np.zeros(0, k), *(g[i] for g in got)]) for i, k in ((0, np.int64), (1, np.int32))]
                lists = [pa.ListArray.from_arrays(pa.array(ends), pa.array(f)) for f in flat]
                yield pa.RecordBatch.from_arrays([p.column("doc_id"), *lists, pa.array([int(c.sum()) for _, c in got], pa.int64()), pa.array([len(t) for t, _ in got], pa.int32())], names=["doc_id", "terms", "counts", "length", "width"])
                del got, flat, lists
        give_back()

    rows = docs.where("doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(read, "doc_id bigint, terms array<bigint>, counts array<int>, length bigint, width int")


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Flat values and lengths."""
    return column.flatten().to_numpy(zero_copy_only=False), column.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)


def _spread(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Positions of several ranges, one after the other."""
    total = int(lengths.sum())
    return np.repeat(starts - (np.cumsum(lengths) - lengths), lengths) + np.arange(total)


class Queries:
    """A pack of queries: their different terms as numbers in one sorted vocabulary, weighted by idf."""

    def __init__(self, ids: np.ndarray, flat: np.ndarray, lengths: np.ndarray):
        self.ids = ids
        self.vocabulary, self.terms = np.unique(flat, return_inverse=True)
        self.ends = np.concatenate([[0], np.cumsum(lengths)])
        self.idf, self.mean = np.zeros(len(self.vocabulary)), 1.0

    def number(self, flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of hashes in the vocabulary, and which of them are in it."""
        at = np.minimum(np.searchsorted(self.vocabulary, flat), max(0, len(self.vocabulary) - 1))
        return at, (self.vocabulary[at] == flat if len(self.vocabulary) else np.zeros(len(flat), bool))

    def weigh(self, df: np.ndarray, n: int, mean: float) -> None:
        self.idf, self.mean = np.log1p((n - df + 0.5) / (df + 0.5)), mean

    def of(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        own = slice(self.ends[i], self.ends[i + 1])
        return self.terms[own], self.idf[self.terms[own]]


def _kinds(flat: np.ndarray, counts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Order of documents by their most frequent term, then by their number of terms; any order is right, this one keeps like ones together."""
    has = np.flatnonzero(lengths)
    starts = (np.cumsum(lengths) - lengths)[has]
    most = np.zeros(len(lengths), np.int64)
    if len(has):
        top = np.repeat(np.maximum.reduceat(counts, starts), lengths[has])
        most[has] = np.minimum.reduceat(np.where(counts == top, flat, np.iinfo(np.int64).max), starts)
    return np.lexsort((lengths, most))


class Shard:
    """Posting lists with maxima by list and block, and forward lists, over the terms of a pack."""

    def __init__(self, queries: Queries, ids: np.ndarray, flat: np.ndarray, counts: np.ndarray, lengths: np.ndarray, sizes: np.ndarray):
        n, order = len(ids), _kinds(flat, counts, lengths)
        self.ids, sizes, at = ids[order], sizes[order], _spread((np.cumsum(lengths) - lengths)[order], lengths[order])
        flat, counts, lengths = flat[at], counts[at], lengths[order]
        at, known = queries.number(flat)
        doc = np.repeat(np.arange(n, dtype=np.int32), lengths)[known]
        term, tf = at[known].astype(np.int32), counts[known].astype(np.float64)
        del at, known, flat, counts
        gain = tf * (K1 + 1) / (tf + K1 * (1 - B + B * sizes[doc] / queries.mean))
        del tf
        self.doc_terms, self.doc_gains = term, gain
        self.doc_ends = np.concatenate([[0], np.cumsum(np.bincount(doc, minlength=n))])
        order = np.argsort(term, kind="stable")  # documents are in order already
        self.docs, self.gains, term = doc[order].astype(np.intp), gain[order], term[order]
        del order, doc
        terms, self.starts = np.unique(term, return_index=True)
        self.list_of = np.full(len(queries.vocabulary), -1, np.int64)
        self.list_of[terms] = np.arange(len(terms))
        self.sizes = np.diff(np.append(self.starts, len(term)))
        self.tops = np.maximum.reduceat(self.gains, self.starts) if len(term) else np.zeros(0)
        block = self.docs // BLOCK
        self.cut = np.flatnonzero((np.diff(block, prepend=-1) != 0) | (np.diff(term, prepend=-1) != 0)) if len(term) else np.zeros(0, np.int64)
        self.block_of, self.block_top = block[self.cut], np.maximum.reduceat(self.gains, self.cut) if len(self.cut) else np.zeros(0)
        self.cut = np.append(self.cut, len(term))
        self.block_starts = np.searchsorted(self.cut[:-1], self.starts)
        self.block_sizes = np.diff(np.append(self.block_starts, len(self.block_of)))
        self.blocks = -(-n // BLOCK)
        self.weights = np.zeros(len(queries.vocabulary))
        self.skipped = 0
        # the most frequent lists by document as a table, more of them by block; columns in falling order of length
        common = np.argsort(-self.sizes, kind="stable")[: int((self.sizes * BLOCK_SHARE >= n).sum())][:BLOCK_COLUMNS]
        self.column_of = np.full(len(terms), BLOCK_COLUMNS, np.int64)
        self.column_of[common] = np.arange(len(common))
        self.columns = min(int((self.sizes * DOC_SHARE >= n).sum()), DOC_COLUMNS)
        of = np.repeat(self.column_of, self.sizes)
        at = np.flatnonzero(of < self.columns)
        self.doc_table = np.zeros((n, self.columns), np.float32)
        self.doc_table[self.docs[at], of[at]] = self.gains[at]
        of = np.repeat(self.column_of, self.block_sizes)
        at = np.flatnonzero(of < BLOCK_COLUMNS)
        self.block_table = np.zeros((self.blocks, len(common)), np.float32)
        self.block_table[self.block_of[at], of[at]] = self.block_top[at]

    def full(self, docs: np.ndarray) -> np.ndarray:
        """Scores of documents from their forward lists, under self.weights."""
        lengths = self.doc_ends[docs + 1] - self.doc_ends[docs]
        at = _spread(self.doc_ends[docs], lengths)
        return np.bincount(np.repeat(np.arange(len(docs)), lengths), weights=self.doc_gains[at] * self.weights[self.doc_terms[at]], minlength=len(docs))

    def best(self, terms: np.ndarray, weights: np.ndarray, k: int, floor: float) -> tuple[np.ndarray, np.ndarray]:
        """Positions and scores of all documents that may be among the k best, given the k-th best score so far (0: none yet)."""
        return self.best_of([(terms, weights)], k, np.array([floor]))[0]

    def best_of(self, asked: list[tuple[np.ndarray, np.ndarray]], k: int, floors: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        """The same for several queries side by side: a block is read if any of them needs it."""
        n, q = len(self.ids), len(asked)
        lists, w = self.list_of[np.concatenate([t for t, _ in asked])], np.concatenate([x for _, x in asked])
        of = np.repeat(np.arange(q), [len(t) for t, _ in asked])[lists >= 0]
        w, lists = w[lists >= 0], lists[lists >= 0]
        column = self.column_of[lists]
        table = np.zeros((q, self.block_table.shape[1]), np.float32)
        at = np.flatnonzero(column < BLOCK_COLUMNS)
        table[of[at], column[at]] = w[at]
        bound = (table @ self.block_table.T).astype(np.float64)
        table = np.ascontiguousarray(table[:, : self.columns])
        at = np.flatnonzero(column >= self.columns)  # lists outside the table of documents, by (query, list, block)
        counts = self.block_sizes[lists[at]]
        parts = _spread(self.block_starts[lists[at]], counts)
        owner, own = np.repeat(of[at].astype(np.int32), counts), self.block_of[parts]
        rest = np.flatnonzero(np.repeat(column[at] == BLOCK_COLUMNS, counts))
        wide = np.repeat(w[at], counts)
        bound += np.bincount(owner[rest] * self.blocks + own[rest], weights=self.block_top[parts[rest]] * wide[rest], minlength=bound.size).reshape(bound.shape)
        del rest, counts, lists, column, of, w
        todo = (bound > 0).any(axis=0)
        floors, found, place = floors.astype(np.float64), [[] for _ in asked], np.zeros(self.blocks, np.int64)
        kept = [np.zeros(0) for _ in asked]
        run = RUN if floors.all() else 0  # with no score to beat yet, the blocks of the largest bounds come first
        while True:
            low = floors * (1 - SLACK)
            ahead = np.flatnonzero(todo & (bound >= np.maximum(low, 1e-300)[:, None]).any(axis=0))
            if not len(ahead):
                break
            if run:
                chosen = ahead[:run]
                gone = todo[: chosen[-1]]  # blocks before the last of the run that are not in it stay below the k-th best scores, which only rise
                self.skipped += q * (int(gone.sum()) - len(chosen) + 1)
                gone[:] = False
            else:
                chosen = np.unique(np.where(todo, bound, -1.0)[floors == 0].argmax(axis=1))[:RUN]
                chosen = chosen[todo[chosen]]
            todo[chosen] = False
            run = RUN
            place[chosen] = np.arange(1, len(chosen) + 1)
            docs = (chosen[:, None] * BLOCK + np.arange(BLOCK)).ravel()
            docs = docs[docs < n]  # only the last block may be smaller
            rows = self.doc_table[docs[0] : docs[-1] + 1] if docs[-1] - docs[0] + 1 == len(docs) else self.doc_table[docs]
            at = np.flatnonzero(place[own])
            starts = self.cut[parts[at]]
            sizes = self.cut[parts[at] + 1] - starts
            into = owner[at] * len(docs) + (place[own[at]] - 1 - own[at]) * BLOCK
            at, post = np.repeat(wide[at], sizes), _spread(starts, sizes)
            sums = np.bincount(np.repeat(into, sizes) + self.docs[post], weights=self.gains[post] * at, minlength=q * len(docs)).reshape(q, len(docs)) + table @ rows.T
            place[chosen] = 0
            alive = sums >= np.maximum(low, 1e-300)[:, None]
            for i in np.flatnonzero(alive.any(axis=1)).tolist():
                at = np.flatnonzero(alive[i])
                found[i].append((docs[at], sums[i, at]))
                kept[i] = np.concatenate([kept[i], sums[i, at]])
                if len(kept[i]) >= k:
                    kept[i] = np.partition(kept[i], len(kept[i]) - k)[len(kept[i]) - k :]
                    floors[i] = max(floors[i], float(kept[i][0]) * (1 - SLACK))
        self.skipped += q * int(todo.sum())
        out = []
        for (terms, weights), near, floor in zip(asked, found, floors):
            docs, scores = (np.concatenate([np.zeros(0, t), *(x[j] for x in near)]) for j, t in enumerate((np.int64, np.float64)))
            docs = docs[scores >= floor * (1 - SLACK)]
            if len(docs):
                self.weights[terms] = weights
                scores = self.full(docs)  # in one order of terms, so that equal documents score alike in every shard
                self.weights[terms] = 0
                if len(scores) > k:
                    floor = max(floor, float(np.partition(scores, len(scores) - k)[len(scores) - k]))
            out.append((docs[scores >= floor], scores[scores >= floor]) if len(docs) else (docs, np.zeros(0)))
        return out


def _matched(index: DataFrame, sent) -> np.ndarray:
    """Document frequency of each term of the pack over all documents."""

    def count(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = sent.value
        df = np.zeros(len(q.vocabulary), np.int64)
        for b in it:
            at, known = q.number(_lists(b.column("terms"))[0])
            df += np.bincount(at[known], minlength=len(df))
        has = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(has), pa.array(df[has])], names=["term", "df"])

    rows = index.select("terms").mapInArrow(count, "term bigint, df bigint").groupBy("term").agg(F.sum("df").alias("df")).toArrow()
    out = np.zeros(len(sent.value.vocabulary), np.int64)
    out[rows.column("term").to_numpy()] = rows.column("df").to_numpy()
    return out


def _searcher(sent, k: int, shard: int):
    def search(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = sent.value
        top: list[list[tuple[float, int]]] = [[] for _ in q.ids]
        held, n, postings = [], 0, 0

        def run() -> None:
            cols = pa.Table.from_batches(held).combine_chunks()
            held.clear()
            flat, lengths = _lists(cols.column("terms").combine_chunks())
            s = Shard(q, cols.column("doc_id").to_numpy(), flat, _lists(cols.column("counts").combine_chunks())[0], lengths, cols.column("length").to_numpy())
            del cols, flat, lengths
            for lo in range(0, len(q.ids), GROUP):
                some = range(lo, min(lo + GROUP, len(q.ids)))
                floors = np.array([-top[i][-1][0] if len(top[i]) == k else 0.0 for i in some])
                for i, (at, scores) in zip(some, s.best_of([q.of(i) for i in some], k, floors)):
                    if len(at):
                        top[i] = sorted(top[i] + [(-x, d) for x, d in zip(scores.tolist(), s.ids[at].tolist())])[:k]

        for b in it:
            for lo in range(0, b.num_rows, SLICE):
                held.append(b.slice(lo, SLICE))
                n += held[-1].num_rows
                postings += int(pa.compute.sum(pa.compute.list_value_length(held[-1].column("terms"))).as_py() or 0)
                if n >= shard or postings >= SHARD_POSTINGS:
                    run()
                    n = postings = 0
        if n:
            run()
        rows = [(int(q.ids[i]), d, -s) for i, found in enumerate(top) for s, d in found]
        del top, held
        give_back()
        yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], t) for j, t in enumerate((pa.int64(), pa.int64(), pa.float64()))], names=["query_id", "doc_id", "score"])

    return search


def search(docs: DataFrame, is_query, k: int = 10, pack: int | None = None, shard: int = SHARD, pack_terms: int = PACK_TERMS) -> DataFrame:
    """query_id, rank, doc_id, score: the k best documents of each query, a query being the whole text of a row for which is_query holds.

    Queries go in packs of bounded terms (and of at most pack queries, if given), each against all shards; what a pack finds is written
    before the next begins.
    """
    spark = docs.sparkSession
    index = materialise(forward_index(docs), "bm25-index")
    n, words, asked, terms = index.agg(F.count(F.lit(1)), F.sum("length"), F.count_if(is_query), F.sum(F.when(is_query, F.col("width")))).first()
    packs = max(1, -(-(terms or 0) // max(1, pack_terms // 2)), -(-asked // max(1, pack // 2)) if pack else 1)
    folder, schema = fresh_dir(spark, "bm25-found"), "query_id bigint, doc_id bigint, score double"
    spark.createDataFrame([], schema).write.parquet(folder)
    for p in range(packs if words else 0):
        rows = index.where(is_query & (F.pmod(F.xxhash64("doc_id"), F.lit(packs)) == p)).select("doc_id", "terms", "counts").toArrow().combine_chunks()
        if not rows.num_rows:
            continue
        flat, lengths = _lists(rows.column("terms").combine_chunks())
        order = _kinds(flat, _lists(rows.column("counts").combine_chunks())[0], lengths)  # like queries go side by side
        flat, lengths = flat[_spread((np.cumsum(lengths) - lengths)[order], lengths[order])], lengths[order]
        queries = Queries(rows.column("doc_id").to_numpy()[order], flat, lengths)
        queries.weigh(_matched(index, spark.sparkContext.broadcast(queries)), n, words / n)
        index.mapInArrow(_searcher(spark.sparkContext.broadcast(queries), k, shard), schema).write.mode("append").parquet(folder)
    every = spark.read.schema(schema).parquet(folder)
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "doc_id")
    return every.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "doc_id", "score")


def op7_search(spark, sf_dir: str) -> DataFrame:
    return search(spark.read.parquet(f"{sf_dir}/documents.parquet"), F.col("doc_id") % 100 == 0)
