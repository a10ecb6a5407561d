"""SimHash near-duplicates: pigeonhole blocks propose pairs, Hamming distance decides, components gather them.

A fingerprint has 64 bits in six blocks. Two that differ in at most three bits agree in at least three whole blocks, so each of
the 20 choices of three blocks is a key, and pairs meet under one of them. Only different fingerprints enter: exact copies cost
one row. Of each key's group only a spanning forest of its links leaves the task, never all pairs. A group above GROUP
fingerprints is split again: its free bits form eight small blocks of which at most three differ, so 56 finer keys with at most
2**13 fingerprints each find the same links.

One fingerprint of three-word shingles within three bits finds copies with very few edits only. dedup therefore adds bands of minima of
hashes of the five-word shingles: an unchanged part of a text keeps its minima whatever else is inserted or cut, and two texts of
similarity s agree on a band with probability s**ROWS. Texts that share a key are candidates; the exact Jaccard similarity of their sets
of five-word shingles decides (SIMILAR or more). dedup goes by ascending id: a text stays unless it is that similar to one that stays, so each one dropped has a
direct, verified link to a kept one. A key's texts are compared with its first few first, and with more of them where that leaves
some open; a group of near copies is mostly gone before all its pairs would be made. Before any text is fetched, a pair must pass a bound
that no pair of SIMILAR or more can fail: of each set of shingles 512 parity bits are kept, of which every shingle flips one, so two sets
differ in at least as many shingles as bits. It is part of the join, which gives out only what passes.

Defined cases: null and empty text have no words and fingerprint zero, and link like any other; documents of null id get a
component by their fingerprint and are never dropped by dedup; repeated rows stay rows (dedup keeps one per id and text); an empty table
gives an empty result; extra columns are ignored by components and kept by dedup.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache, reduce
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators.components import connected_components
from ..storage import materialise
from .columns import unused

SEED, SHINGLE, DISTANCE = 42, 3, 3
#: Widths of the blocks, of which DISTANCE may differ.
BLOCKS = (11, 11, 11, 11, 10, 10)
#: Fingerprints of a group that one task compares directly.
GROUP = 4096
#: Bands of minima that dedup takes beside the fingerprint, and minima in a band: at similarity 0.8 all differ for one pair in 13000.
BANDS, ROWS = 18, 4
#: Words of a shingle and Jaccard similarity by which dedup calls two texts copies; first texts of a key that others meet at first.
WIDE_SHINGLE, SIMILAR, LEADERS = 5, 0.8, 8
#: By how much the number of first texts grows from round to round, and 64-bit words of parity bits.
MORE, PARITY = 8, 8
_CHUNK = 1 << 16


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _key_masks() -> list[int]:
    starts = np.concatenate([[0], np.cumsum(BLOCKS)])
    block = [((1 << w) - 1) << int(s) for w, s in zip(BLOCKS, starts)]
    return [sum(c) for c in combinations(block, len(BLOCKS) - DISTANCE)]


def _finer_masks(mask: int) -> list[int]:
    """mask with all but three of eight small blocks of its free bits added, in the 56 ways."""
    free = [i for i in range(64) if not mask >> i & 1]
    parts = [sum(1 << int(i) for i in p) for p in np.array_split(free, 8)]
    return [mask | sum(c) for c in combinations(parts, 8 - DISTANCE)]


def majority_bits(hashes: np.ndarray) -> int:
    """The 64-bit number whose bits are set in over half of the hashes."""
    lanes = np.uint64(0x0101010101010101)
    totals = np.zeros((8, 8), np.int64)  # bit in byte, byte
    for bit in range(8):
        ones = (hashes >> np.uint64(bit)) & lanes  # a byte lane of 0 or 1 for each byte
        at = np.arange(0, len(ones), 255)
        totals[bit] = np.add.reduceat(ones, at).view(np.uint8).reshape(-1, 8).sum(axis=0, dtype=np.int64)
    over = 2 * totals > len(hashes)
    return sum(1 << (8 * byte + bit) for bit in range(8) for byte in range(8) if over[bit, byte])


def fingerprint(text: str | None) -> int:
    """SimHash of the shingles of a text, repeats included."""
    from xxhash import xxh64_intdigest

    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return 0
    if len(words) < SHINGLE:
        return xxh64_intdigest(b" ".join(words), SEED)
    shingles = map(b" ".join, zip(*(words[i:] for i in range(SHINGLE))))
    return majority_bits(np.fromiter(map(xxh64_intdigest, shingles, repeat(SEED)), np.uint64, len(words) - SHINGLE + 1))


def shingle_set(text: str | None) -> np.ndarray:
    """Sorted different hashes of the five-word shingles of a text; fewer words are one shingle, no words none."""
    from xxhash import xxh64_intdigest

    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    if len(words) < WIDE_SHINGLE:
        return np.array([xxh64_intdigest(b" ".join(words), SEED)], np.uint64)
    hashes = np.fromiter(map(xxh64_intdigest, words, repeat(SEED)), np.uint64, len(words))
    n = len(words) - WIDE_SHINGLE + 1
    out = np.zeros(n, np.uint64)
    for i in range(WIDE_SHINGLE):
        out = (out ^ out >> np.uint64(29)) * np.uint64(0x9E3779B97F4A7C15) + hashes[i : i + n]
    return np.unique(out)


def parity_bits(shingles: np.ndarray) -> np.ndarray:
    """64 x PARITY bits, of which each shingle flips one."""
    counts = np.bincount((shingles >> np.uint64(20)) % np.uint64(64 * PARITY), minlength=64 * PARITY)
    return np.packbits((counts & 1).astype(np.uint8)).view(np.int64)


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Of two shingle sets; two empty ones are equal."""
    both = np.concatenate([a, b])
    both.sort()
    common = int((both[1:] == both[:-1]).sum())
    return common / (len(both) - common) if len(both) else 1.0


@cache
def _mask_array() -> np.ndarray:
    return np.array(_key_masks(), np.uint64)


@cache
def _mixes(n: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(SEED)
    return rng.integers(0, 1 << 64, n, np.uint64), rng.integers(0, 1 << 64, n, np.uint64) | np.uint64(1)


def candidate_keys(text: str | None, shingles: np.ndarray, bands: int) -> np.ndarray:
    """Numbers of which near copies share one: three of six blocks of the fingerprint, and bands of minima of the shingles, named by kind and place."""
    masks = _mask_array()
    add, times = _mixes(bands * ROWS)
    least = np.full(bands * ROWS, np.iinfo(np.uint64).max)
    for i in range(0, len(shingles), 128):
        least = np.minimum(least, ((shingles[i : i + 128, None] ^ add) * times).min(axis=0))
    band = np.zeros(bands, np.uint64)
    for row in least.reshape(bands, ROWS).T:
        band = (band ^ band >> np.uint64(29)) * np.uint64(0x9E3779B97F4A7C15) + row
    values = np.concatenate([np.uint64(fingerprint(text)) & masks, band])
    return _named(values, np.arange(1, len(values) + 1, dtype=np.uint64))


#: Columns that describe a set of shingles: its size and its parity bits.
SET = ["size", *(f"bits{i}" for i in range(PARITY))]
_SET_DDL = ", ".join(f"{c} {'int' if c == 'size' else 'bigint'}" for c in SET)


def _may_be_similar() -> Column:
    """Of columns size, bits0, … and the same with _a: false only where fewer than SIMILAR of the shingles can be in common."""
    differ = reduce(lambda x, y: x + y, (F.bit_count(F.col(c).bitwiseXOR(F.col(f"{c}_a"))) for c in SET[1:]))
    return differ * F.lit(1 + SIMILAR) <= (F.col("size") + F.col("size_a")) * F.lit(1 - SIMILAR) + F.lit(1e-6)


def _named(values: np.ndarray, names: np.ndarray) -> np.ndarray:
    """Values of different names made different."""
    h = (values ^ names * np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xD6E8FEB86659FD93)
    return (h ^ h >> np.uint64(32)) * np.uint64(0x9E3779B97F4A7C15) ^ names


def _key_batches(bands: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh64_intdigest

        for b in batches:
            nodes, keys, bits, sizes = np.zeros(b.num_rows, np.uint64), [], np.zeros((b.num_rows, PARITY), np.int64), np.zeros(b.num_rows, np.int32)
            for i, t in enumerate(x.as_py() for x in b.column("text")):
                shingles = shingle_set(t)
                nodes[i] = xxh64_intdigest(shingles.tobytes(), SEED)
                bits[i], sizes[i] = parity_bits(shingles), len(shingles)
                keys.append(candidate_keys(t, shingles, bands).view(np.int64))
            ends = np.cumsum([0, *map(len, keys)]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.zeros(0, np.int64), *keys])))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("hashed"), pa.array(nodes.view(np.int64)), lists, pa.array(sizes), *(pa.array(c.copy()) for c in bits.T)], names=["doc_id", "hashed", "node", "keys", *SET])

    return run


def _verify_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Adds whether the texts of a and b are copies; the sets of a run of equal a are made once."""
    last, held = None, None
    for batch in batches:
        near = []
        for a, ta, tb in zip(*(batch.column(c).to_pylist() for c in ("a", "text_a", "text_b"))):
            if a != last:
                last, held = a, shingle_set(ta)
            near.append(jaccard(held, shingle_set(tb)) >= SIMILAR)
        yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(near, pa.bool_())], names=["a", "b", "near"])


def _fingerprint_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        fps = np.fromiter((fingerprint(t.as_py()) for t in b.column("text")), np.uint64, b.num_rows).view(np.int64)
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(fps)], names=["doc_id", "fp"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id and fp, a row per document."""
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    kind = docs.schema["doc_id"].dataType.simpleString()
    return rows.mapInArrow(_fingerprint_batches, f"doc_id {kind}, fp bigint")


def forest(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Star edges (root, member) of the components of different fingerprints at DISTANCE or less."""
    rest, roots, members = np.sort(fps), [], []
    while rest.size > 1:
        root, rest = rest[0], rest[1:]
        front = np.array([root])
        while front.size and rest.size:
            near = np.zeros(rest.size, bool)
            for i in range(0, front.size, 256):
                near |= (np.bitwise_count(front[i : i + 256, None] ^ rest[None, :]) <= DISTANCE).any(axis=0)
            front, rest = rest[near], rest[~near]
            roots.append(np.full(front.size, root))
            members.append(front)
    none = np.zeros(0, np.uint64)
    return np.concatenate([none, *roots]), np.concatenate([none, *members])


def _forest_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        col, kinds = b.column("fps"), b.column("r").to_numpy()
        flat = col.flatten().to_numpy(zero_copy_only=False).view(np.uint64)
        ends = np.cumsum(col.value_lengths().to_numpy(zero_copy_only=False))
        starts = np.concatenate([[0], ends[:-1]]).astype(np.int64)
        pairs = ends - starts == 2
        a, c = flat[starts[pairs]], flat[starts[pairs] + 1] if pairs.any() else flat[:0]
        near = np.bitwise_count(a ^ c) <= DISTANCE
        out = [(kinds[pairs][near], a[near], c[near])]
        for r, s, e in zip(kinds[~pairs], starts[~pairs], ends[~pairs]):
            x, y = forest(flat[s:e])
            out.append((np.full(len(x), r), x, y))
        r, x, y = (np.concatenate(z) for z in zip(*out))
        yield pa.RecordBatch.from_arrays([pa.array(r.astype(np.int32)), pa.array(x.view(np.int64)), pa.array(y.view(np.int64))], names=["r", "a", "b"])


def links(fps: DataFrame) -> DataFrame:
    """Links (r, a, b) between different fingerprints of one kind r: enough of them to connect all that are near. fps: distinct (r, fp)."""
    masks = _key_masks()
    keys = F.array(*(F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("k")) for t, m in enumerate(masks)))
    keyed = fps.select("r", "fp", F.inline(keys))
    sizes = keyed.groupBy("r", "t", "k").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    met = keyed.join(sizes, ["r", "t", "k"])
    groups = met.where(F.col("n") <= GROUP).groupBy("r", "t", "k").agg(F.collect_list("fp").alias("fps")).select("r", "fps")
    finer = F.array(*(F.array(*(F.lit(_signed(m)) for m in _finer_masks(mask))) for mask in masks))
    split = met.where(F.col("n") > GROUP).select("r", "fp", "t", F.posexplode(F.element_at(finer, F.col("t") + 1)).alias("s", "mask"))
    split = split.groupBy("r", "t", "s", F.col("fp").bitwiseAND(F.col("mask")).alias("k")).agg(F.collect_list("fp").alias("fps"))
    return groups.union(split.where(F.size("fps") > 1).select("r", "fps")).mapInArrow(_forest_batches, "r int, a bigint, b bigint").distinct()


def components(docs: DataFrame) -> DataFrame:
    """doc_id, fp, component_id for every row of docs.

    Links carry the least id of each fingerprint, so the component found is the smallest id already and no row is dealt by component.
    """
    rows = materialise(fingerprints(docs), "fingerprints")
    least = materialise(rows.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct-fingerprints")
    at = least.select("fp", F.struct(F.col("least").isNull().alias("lost"), "least", "fp").alias("at"))  # fingerprints of null ids only come last
    near = links(least.select(F.lit(0).alias("r"), "fp")).select("a", "b")
    near = near.join(at.select(F.col("fp").alias("a"), F.col("at").alias("x")), "a").join(at.select(F.col("fp").alias("b"), F.col("at").alias("y")), "b")
    found = connected_components(near, "x", "y").select(F.col("node.fp").alias("fp"), F.col("component.least").alias("found"))
    parts = least.join(found, "fp", "left").select("fp", F.coalesce("found", "least").alias("component_id"))
    return rows.join(parts, "fp")


def _leading(held: DataFrame, n: int) -> DataFrame:
    """The first n nodes of each key by least id; the limit is applied before the shuffle already."""
    first = held.withColumn("place", F.row_number().over(Window.partitionBy("key").orderBy("least", "node")))
    return first.where(F.col("place") <= n).drop("place")


def _represented(nodes: DataFrame, texts: DataFrame) -> DataFrame:
    """node, kept: the node that stands for it, for every node that shares a key with another. nodes: node, least, keys and SET.

    Each round verifies pairs of a key's first nodes with all of its others, more of them every time. A node that is
    among the first under all its keys knows all its earlier neighbours: it stays once none of them is left, and then its later
    neighbours go.
    """
    open_, tested, decided, n = nodes, None, [], LEADERS
    while True:
        held = open_.select("node", "least", *SET, F.explode("keys").alias("key"))
        held = held.join(held.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("key"), "key")
        held = materialise(held, "copy-keys")
        if held.isEmpty():
            return _union(decided + [open_.select("node", F.col("node").alias("kept"))])
        leading = materialise(_leading(held, n), "copy-leaders")
        led = leading.groupBy("node").agg(F.count(F.lit(1)).alias("led"))
        known = held.groupBy("node").agg(F.count(F.lit(1)).alias("all")).join(led, "node", "left").where("led = all").select("node")
        # a node that shares no key any more has no candidate left
        known = materialise(known.union(open_.join(held, "node", "left_anti").select("node")), "copy-known")
        a = leading.select(F.col("key").alias("key_a"), F.col("node").alias("a"), F.col("least").alias("la"), *(F.col(c).alias(f"{c}_a") for c in SET))
        b = held.select("key", F.col("node").alias("b"), F.col("least").alias("lb"), *SET)
        earlier = (F.col("la") < F.col("lb")) | (F.col("la") == F.col("lb")) & (F.col("a") < F.col("b"))
        pairs = b.join(a, (F.col("key") == F.col("key_a")) & earlier & _may_be_similar()).select("a", "b").distinct()
        if tested is not None:
            pairs = pairs.join(tested, ["a", "b"], "left_anti")
        with_texts = pairs.join(texts.select(F.col("node").alias("b"), F.col("text").alias("text_b")), "b").join(texts.select(F.col("node").alias("a"), F.col("text").alias("text_a")), "a")
        new = materialise(with_texts.select("a", "b", "text_a", "text_b").mapInArrow(_verify_batches, "a bigint, b bigint, near boolean"), "copy-pairs")
        tested = new if tested is None else tested.unionByName(new)
        ids = open_.select("node", "least")
        edges = tested.where("near").select("a", "b").join(ids.select(F.col("node").alias("a"), "least"), "a").join(ids.select(F.col("node").alias("b")), "b")
        while True:
            edges = materialise(edges, "copy-links")
            stay = known.join(edges.select(F.col("b").alias("node")), "node", "left_anti")
            gone = edges.join(stay, edges["a"] == stay["node"], "left_semi").groupBy("b").agg(F.min(F.struct("least", "a")).alias("first"))
            done = materialise(stay.select("node", F.col("node").alias("kept")).union(gone.select("b", "first.a")), "copy-decided")
            if done.isEmpty():
                break
            decided.append(done)
            over = done.select("node")
            known = materialise(known.join(over, "node", "left_anti"), "copy-known")
            edges = edges.join(over, edges["a"] == over["node"], "left_anti").join(over, edges["b"] == over["node"], "left_anti")
            open_ = open_.join(over, "node", "left_anti")
        open_ = materialise(open_, "copy-open")
        if open_.isEmpty():
            return _union(decided)
        n *= MORE


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _copies(docs: DataFrame, bands: int) -> DataFrame:
    """Of every row of docs doc_id, hashed (of the text), component_id, the id of the kept document that stands for it, and whether it is that one."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    text = docs.select("doc_id", F.col("text").cast("string").alias("text")).withColumn("hashed", F.xxhash64("text"))
    rows = materialise(text.mapInArrow(_key_batches(bands), f"doc_id {kind}, hashed bigint, node bigint, keys array<bigint>, {_SET_DDL}"), "copy-rows")
    whole = rows.where("doc_id IS NOT NULL").groupBy("node").agg(F.min(F.struct("doc_id", "hashed")).alias("first"), F.first("keys").alias("keys"), *(F.first(c).alias(c) for c in SET))
    nodes = materialise(whole.select("node", F.col("first.doc_id").alias("least"), F.col("first.hashed").alias("hashed"), "keys", *SET), "copy-nodes")
    held = nodes.select("node", F.explode(F.array_distinct("keys")).alias("key"))
    met = held.join(held.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "key").groupBy("node").agg(F.collect_list("key").alias("keys"))
    some = materialise(nodes.drop("keys").join(met, "node"), "copy-candidates")
    texts = materialise(some.join(text.withColumnRenamed("doc_id", "least"), ["least", "hashed"]).select("node", "text").dropDuplicates(["node"]), "copy-texts")
    stands = materialise(_represented(some.select("node", "least", "keys", *SET), texts), "copy-stands")
    kept = nodes.select(F.col("node").alias("kept"), F.col("least").alias("component_id"), F.col("hashed").alias("first"))
    to = nodes.select("node").join(stands, "node", "left").select("node", F.coalesce("kept", "node").alias("kept")).join(kept, "kept")
    stays = (F.col("node") == F.col("kept")) & (F.col("doc_id") == F.col("component_id")) & (F.col("hashed") == F.col("first"))
    return rows.select("doc_id", "hashed", "node").join(to, "node", "left").select("doc_id", "hashed", "component_id", stays.alias("stays"))


def wide_components(docs: DataFrame, bands: int = BANDS) -> DataFrame:
    """doc_id, component_id: the id of the kept document that the row equals or is similar to; null where only null ids have the text."""
    return _copies(docs, bands).select("doc_id", "component_id")


def dedup(docs: DataFrame, bands: int = BANDS) -> DataFrame:
    """docs without those that are copies of a kept document of a smaller id; rows that repeat an id with another text are other documents."""
    keep = _copies(docs.select("doc_id", "text"), bands).where("stays")
    row, hashed, key = unused(docs, "row", "hashed", "key")
    keep = keep.select(F.col("doc_id").alias(key), F.col("hashed").alias(hashed)).distinct()
    kept = docs.join(keep, (docs["doc_id"] == F.col(key)) & (F.xxhash64(docs["text"].cast("string")) == F.col(hashed)))
    kept = kept.withColumn(row, F.row_number().over(Window.partitionBy(key, hashed).orderBy(key)))
    return kept.where(F.col(row) == 1).select(*(docs[c] for c in docs.columns)).unionByName(docs.where("doc_id IS NULL"))


def op4_simhash(spark, sf_dir: str) -> DataFrame:
    out = components(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
