"""SimHash near-duplicates by covering locality-sensitive hashing.

Every document gets a 64-bit fingerprint (a bit is 1 if it is set in over half of the XXH64 values of the word
shingles).  For radius r, every bit position gets a non-zero vector of r+1 bits, and there is one table for each
non-zero v in {0,1}^(r+1): it keeps the positions whose vector has an odd inner product with v.  The vectors of at
most r differing positions span a space that some v is orthogonal to, so *every* pair within the radius agrees on
all kept bits of some table.

Equal fingerprints are merged before anything is paired.  In a table, documents with equal kept bits are searched
breadth-first with vectorised comparisons, which gives a spanning forest of the bucket, never all its pairs; a bucket
over `block` members is split into pairs of blocks that go to different tasks.  Components come from alternating
star contractions, checkpointed every round.

The pipeline's stage groups by similarity (Jaccard of 5-word shingles, 0.8) rather than by a radius: texts as alike
as that can differ in more bits than covering tables allow.  There the fingerprint is of the set of shingles, without
repeats, and beside the covering tables there are *thinned views*: the SimHash of the smallest few shingle hashes in
each of 32 hash ranges, equal with high probability in at least one range.  These propose pairs; no distance of
fingerprints decides, only the sets themselves.  A bucket of up to 32 gives all its pairs; in a larger one the search itself compares the sets of shingles, so a member is only ever taken
out by a link that holds, and every link of the bucket is either found or between members already connected.  A first search
takes each node in its largest bucket only; then pairs within what that connected are left out, and so are buckets all
of whose members are connected.

Null and empty texts have fingerprint 0. Rows with a null doc_id aren't linked (component null).  Each row has a fingerprint
of its own; rows with the same doc_id share a component, as each other's copies do.  (Where the stage compares sets of
shingles, the row with the greatest set stands for its doc_id.)  Only doc_id and text are read; `stage` returns
all columns as they came.  An empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.llm.core import few_rows, give_back, mix, read_table, reliable

RADIUS = 4
SEED = 42
BLOCK, BLOCK_HASHES = 4096, 1 << 21
VIEWS, VIEW_SIZE, ALL_PAIRS = 32, 6, 32
_BITS = np.array([bin(i).count("1") for i in range(1 << 16)], np.uint8)


def popcount(x: np.ndarray) -> np.ndarray:
    return _BITS[np.ascontiguousarray(x).view(np.uint16).reshape(*x.shape, 4)].sum(-1, dtype=np.int64)


def shingle_hashes(text: str | None, size: int) -> np.ndarray:
    """XXH64 of every run of `size` words (of all words, if they are fewer), repeats included."""
    words = (text or "").encode().lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    line = b" ".join(words)
    if len(words) <= size:
        return np.array([xxhash.xxh64_intdigest(line, SEED)], np.uint64)
    ends = np.cumsum([len(w) + 1 for w in words]).tolist()
    starts = [0, *ends]
    digest, n = xxhash.xxh64_intdigest, len(words) - size + 1
    return np.fromiter((digest(line[starts[i] : ends[i + size - 1] - 1], SEED) for i in range(n)), np.uint64, n)


def majority(hashes: np.ndarray) -> int:
    """Bits set in over half of the hashes."""
    if not len(hashes):
        return 0
    total = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 1 << 16):
        part = hashes[i : i + (1 << 16)]
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(total * 2 > len(hashes), bitorder="little").view(np.uint64)[0])


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def fingerprints(docs: DataFrame, size: int = 4, views: int = 0) -> DataFrame:
    """(doc_id, f, views). f: the SimHash; with views, that of the set of shingles, a digest of the set and its size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints, seen = [], []
            for text in batch.column(1).to_pylist():
                h = shingle_hashes(text, size)
                h = np.unique(h) if views else h
                prints.append([_signed(majority(h)), *([_signed(xxhash.xxh64_intdigest(h.tobytes(), SEED)), len(h)] if views else [])])
                seen.append(thinned(h, views) if views else [])
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0).cast(pa.int64()), "f": pa.array(prints, pa.list_(pa.int64())), "views": pa.array(seen, pa.list_(pa.int64()))})
        give_back()

    return few_rows(docs).select("doc_id", "text").mapInArrow(run, "doc_id long, f array<long>, views array<long>")


def thinned(hashes: np.ndarray, views: int, keep: int = VIEW_SIZE) -> list[int]:
    """A fingerprint of the `keep` smallest distinct hashes in each of `views` hash ranges that isn't empty."""
    h = np.unique(hashes)
    cuts = np.searchsorted(h, np.array([(v << 64) // views for v in range(1, views)], dtype=object).astype(np.uint64))
    return [_signed(majority(part[:keep]) ^ int(mix(np.array([v + 1], np.uint64))[0])) for v, part in enumerate(np.split(h, cuts)) if len(part)]


def covering_masks(radius: int, bits: int = 64) -> list[int]:
    """2^(radius+1)-1 masks; any two words within the radius agree on the bits of one of them."""
    top = (1 << (radius + 1)) - 1
    vector = [1 + (i * 11 + i // top) % top for i in range(bits)]
    return [sum(1 << i for i in range(bits) if bin(vector[i] & v).count("1") % 2) for v in range(1, top + 1)]


def bucket_links(f: np.ndarray, node: np.ndarray, limit: int) -> list[tuple[int, int]]:
    """A spanning forest of the links of rows within `limit` bits.

    The forest grows from the rows nearest to the bitwise majority of the bucket, so that a text and its edited copies
    are linked through the text rather than from copy to copy.
    """
    n = len(node)
    bits = np.unpackbits(f.view(np.uint8).reshape(n, -1), axis=1)
    off = (bits != (bits.sum(0, dtype=np.int64) * 2 > n)).sum(1)
    left, out = np.lexsort((node, off)), []
    while len(left):
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            at = queue.pop(0)
            near = popcount(f[left] ^ f[at]).sum(1) <= limit
            if near.any():
                new = left[near]
                out += [(int(node[at]), int(node[i])) for i in new]
                queue += new.tolist()
                left = left[~near]
    return out


def links(keys: DataFrame, prints: DataFrame, limit: int, block: int = BLOCK) -> DataFrame:
    """Links (a, b) of nodes that share a key of a table and are within `limit` bits.

    keys: (t, key, node). prints: (node, f). The fingerprints join only the buckets of two or more.
    """
    large = keys.groupBy("t", "key").agg(F.count("*").alias("n")).where(F.col("n") >= 2).withColumn("blocks", F.ceil(F.col("n") / block).cast("int"))
    dealt = bucket_blocks(keys.join(large.drop("n"), ["t", "key"])).join(prints, "node").select("node", "f", "bucket")

    def found(frame: pd.DataFrame) -> list[tuple[int, int]]:
        return bucket_links(np.stack(frame["f"].to_numpy()).astype(np.int64).view(np.uint64), frame["node"].to_numpy(np.int64), limit)

    return by_bucket(dealt, found)


def bucket_blocks(held: DataFrame) -> DataFrame:
    """(t, key, node, blocks) -> (node, bucket): a bucket for every pair of blocks of a key."""
    held = held.withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    pair = F.when(F.col("blocks") == 1, F.array(F.lit("0"))).otherwise(
        F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda j: F.concat(F.least(j, F.col("own")).cast("string"), F.lit("-"), F.greatest(j, F.col("own")).cast("string")))
    )
    return held.select("node", "t", "key", F.explode(pair).alias("pair")).select("node", F.xxhash64("t", "key", "pair").alias("bucket"))


def by_bucket(dealt: DataFrame, links_of) -> DataFrame:
    """Links (a, b) that links_of gives for the rows of every bucket of two or more."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        kept: pd.DataFrame | None = None
        for frame in frames:
            frame = frame if kept is None else pd.concat([kept, frame], ignore_index=True)
            bucket = frame["bucket"].to_numpy()
            at = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
            kept = frame.iloc[at[-1] :]
            yield found(frame, at[:-1], at[1:])
        if kept is not None:
            yield found(kept, np.array([0]), np.array([len(kept)]))
        kept = None
        give_back()

    def found(frame: pd.DataFrame, lo: np.ndarray, hi: np.ndarray) -> pd.DataFrame:
        out: list[tuple[int, int]] = []
        for i, j in zip(lo.tolist(), hi.tolist(), strict=True):
            if j - i > 1:
                out += links_of(frame.iloc[i:j])
        return pd.DataFrame(out, columns=["a", "b"], dtype=np.int64)

    return dealt.repartition("bucket").sortWithinPartitions("bucket").mapInPandas(run, "a long, b long").where("a != b").distinct()


def all_pairs(keys: DataFrame, similarity: float) -> DataFrame:
    """(a, b), a < b: the pairs of nodes that share a key of a table, have different roots, and whose sets' sizes allow the
    similarity: the smaller is at least that share of the larger. For buckets of few members. keys: (t, key, node, size, root)."""
    members = keys.groupBy("t", "key").agg(F.array_sort(F.collect_set(F.struct("node", "size", "root"))).alias("m")).select("m").distinct()
    both = members.select("m", F.explode("m").alias("x")).select("x", F.explode("m").alias("y")).where("x.node < y.node")
    fits = F.least("x.size", "y.size") >= F.greatest("x.size", "y.size") * similarity - 1e-9
    return both.where("x.root != y.root").where(fits).select(F.col("x.node").alias("a"), F.col("y.node").alias("b")).distinct()


def forest(sets: list[np.ndarray], node: np.ndarray, similarity: float) -> list[tuple[int, int]]:
    """A spanning forest of the rows whose sets have at least this Jaccard similarity, grown from the most typical row.

    The shingles that rows share are found through an index of the rows not reached yet, made anew as they get fewer.
    """
    n, size = len(node), np.array([len(x) for x in sets])
    _, col = np.unique(np.concatenate(sets), return_inverse=True)
    at, width = np.concatenate([[0], np.cumsum(size)]), int(col.max(initial=-1)) + 1
    left, out = np.ones(n, bool), []
    typical = np.bincount(np.repeat(np.arange(n), size), np.bincount(col, minlength=width)[col], minlength=n)
    order, indexed = np.lexsort((node, -typical)).tolist(), 0
    for root in order:
        if not left[root]:
            continue
        left[root], queue = False, [root]
        while queue and left.any():
            if (here := int(left.sum())) * 2 <= indexed or not indexed:
                rows = np.flatnonzero(left)
                cols = np.concatenate([col[at[i] : at[i + 1]] for i in rows])
                owner = np.repeat(rows, size[rows])[np.argsort(cols, kind="stable")]
                ends = np.cumsum(np.bincount(cols, minlength=width))
                starts, indexed = np.concatenate([[0], ends[:-1]]), here
            i = queue.pop()
            own = col[at[i] : at[i + 1]]
            lo, many = starts[own], ends[own] - starts[own]
            hits = np.repeat(lo - np.cumsum(many) + many, many) + np.arange(int(many.sum()))
            both = np.bincount(owner[hits], minlength=n)
            new = np.flatnonzero(left & (both >= similarity * (size + size[i] - both)))
            out += [(int(node[i]), int(node[j])) for j in new]
            queue += new.tolist()
            left[new] = False
    return out


def crowded(keys: DataFrame, docs: DataFrame, size: int, similarity: float, block: int = BLOCK, hashes: int = BLOCK_HASHES) -> DataFrame:
    """Links (a, b) that connect what similar texts connect in every bucket of (t, key, node), of any number of members.

    Buckets of the same members are searched once. One over `block` members or `hashes` shingles is split into pairs of
    blocks, which together hold all its pairs.
    """
    keys = reliable(keys.select("t", "key", "node").distinct())
    h = reliable(shingle_sets(docs, keys.select("node").distinct(), size))
    sized = keys.join(h.select(F.col("id").alias("node"), (F.octet_length("h") / 8).cast("long").alias("w")), "node")
    same = F.count("*").alias("n"), F.bit_xor(F.xxhash64("node")).alias("x"), F.bit_xor(F.xxhash64("node", F.lit(SEED))).alias("y"), F.sum("w").alias("w")
    once = sized.groupBy("t", "key").agg(*same).groupBy("n", "x", "y", "w").agg(F.min(F.struct("t", "key")).alias("k"))
    blocks = F.greatest(F.ceil(F.col("n") / block), F.ceil(F.col("w") / hashes)).cast("int")
    dealt = bucket_blocks(keys.join(once.select("k.t", "k.key", blocks.alias("blocks")), ["t", "key"])).join(h.withColumnRenamed("id", "node"), "node")

    def found(frame: pd.DataFrame) -> list[tuple[int, int]]:
        return forest([np.frombuffer(x, np.uint64) for x in frame["h"]], frame["node"].to_numpy(np.int64), similarity)

    return by_bucket(dealt.select("node", "h", "bucket"), found)


def components(edges: DataFrame) -> DataFrame:
    """(node, root): the smallest node that each node of an edge is connected with. Large-star and small-star rounds."""
    state = reliable(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v").distinct())
    mark = None
    while True:
        both = state.union(state.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        state = reliable(small.distinct())
        now = state.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == mark:
            return state.select(F.col("u").alias("node"), F.col("v").alias("root"))
        mark = now


def grouped(prints: DataFrame, limit: int = RADIUS, radius: int = RADIUS, find=None) -> DataFrame:
    """prints: (doc_id, f, views) -> (doc_id, f, component_id). find: links of keys other than by `limit` bits."""
    prints = reliable(prints)
    distinct = reliable(prints.where(F.col("doc_id").isNotNull()).groupBy("f", "views").agg(F.min("doc_id").alias("node")))
    masks = covering_masks(radius)
    tables = F.array(*(F.struct(F.lit(t).alias("t"), F.col("f")[0].bitwiseAND(F.lit(_signed(m))).alias("key")) for t, m in enumerate(masks)))
    seen = F.transform("views", lambda k: F.struct(F.lit(-1).alias("t"), k.alias("key")))
    keys = distinct.select("node", F.get("f", F.lit(2)).alias("size"), F.explode(F.concat(tables, seen)).alias("k")).select("k.t", "k.key", "node", "size")
    found = find(keys) if find else links(keys, distinct.select("node", "f"), limit)
    roots = components(found.select("a", "b").union(same_ids(prints, distinct)))
    named = distinct.join(roots, "node", "left").select("f", "views", F.coalesce("root", "node").alias("component_id"))
    linked = prints.join(named, ["f", "views"], "left")
    return linked.select("doc_id", "f", F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))


def same_ids(prints: DataFrame, distinct: DataFrame) -> DataFrame:
    """Links (a, b) of a doc_id with the nodes of its rows, where those have different prints."""
    own = prints.where(F.col("doc_id").isNotNull()).select("doc_id", F.xxhash64("f", "views").alias("x"))
    several = own.groupBy("doc_id").agg(F.min("x").alias("low"), F.max("x").alias("high")).where("low != high").select("doc_id")
    return prints.join(several, "doc_id").join(distinct, ["f", "views"]).select(F.col("doc_id").alias("a"), F.col("node").alias("b")).where("a != b")


def shingle_sets(docs: DataFrame, nodes: DataFrame, size: int) -> DataFrame:
    """(id, h): the sorted set of shingle hashes of the texts named by the only column of nodes."""

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held = [np.unique(shingle_hashes(t, size)).tobytes() for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_pydict({"id": batch.column(0).cast(pa.int64()), "h": pa.array(held, pa.binary())})
        give_back()

    texts = docs.select("doc_id", "text").join(nodes.toDF("n"), F.col("doc_id") == F.col("n"), "left_semi")
    return texts.mapInArrow(sets, "id long, h binary").groupBy("id").agg(F.max("h").alias("h"))


def alike(found: DataFrame, docs: DataFrame, size: int, similarity: float) -> DataFrame:
    """The links whose texts have at least this Jaccard similarity of their sets of shingles."""

    def hold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                both = len(np.intersect1d(x, y, True))
                keep.append(both >= similarity * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([c.filter(pa.array(keep, pa.bool_())) for c in batch.columns[:2]], ["a", "b"])
        give_back()

    nodes = found.select(F.col("a").alias("n")).union(found.select("b")).distinct()
    h = reliable(shingle_sets(docs, nodes, size))
    one, two = h.select(F.col("id").alias("a"), F.col("h").alias("ha")), h.select(F.col("id").alias("b"), F.col("h").alias("hb"))
    return found.join(one, "a").join(two, "b").select("a", "b", "ha", "hb").mapInArrow(hold, "a long, b long")


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = grouped(fingerprints(read_table(spark, sf_dir, "documents")), RADIUS)
    return found.select("doc_id", F.lpad(F.lower(F.hex(F.col("f")[0])), 16, "0").alias("fingerprint"), "component_id")


def near_groups(docs: DataFrame, similarity: float = 0.8, size: int = 5) -> DataFrame:
    """(doc_id, component_id) by similarity of word shingles; every link is verified with the shingles themselves."""

    def find(keys: DataFrame) -> DataFrame:
        n = keys.groupBy("t", "key").agg(F.count("*").alias("n")).where("n >= 2")
        held = reliable(keys.join(n, ["t", "key"]))
        many = held.where(F.col("n") > ALL_PAIRS)
        # each node in its largest bucket first: that joins most of a large group, so that what is left to compare are
        # pairs and buckets over what is not yet connected, and few sets of shingles are sent twice
        largest = many.groupBy("node").agg(F.max(F.struct("n", "t", "key")).alias("k")).select("k.t", "k.key", "node")
        first = reliable(crowded(largest, docs, size, similarity))
        named = reliable(held.join(components(first), "node", "left").withColumn("root", F.coalesce("root", "node")))
        few = all_pairs(named.where(F.col("n") <= ALL_PAIRS), similarity)
        apart = named.where(F.col("n") > ALL_PAIRS).groupBy("t", "key").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low != high")
        rest = many.join(apart.select("t", "key"), ["t", "key"])
        return first.union(alike(reliable(few), docs, size, similarity)).union(crowded(rest, docs, size, similarity))

    return grouped(fingerprints(docs, size, VIEWS), find=find).select("doc_id", "component_id")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the smallest id, with all its rows if there are several; rows with a
    null id stay."""
    dropped = near_groups(docs).where("doc_id != component_id").select(F.col("doc_id").alias("_drop")).distinct()
    kept = docs.join(dropped, docs["doc_id"] == dropped["_drop"], "left_anti")
    return kept
