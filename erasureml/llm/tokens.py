"""Token-id files: Simple-8b word-aligned coding, in blocks that decode on their own.

A 64-bit word is 4 bits of selector and 60 bits of payload.  Selectors 0 to 13 pack a number of ids of a width
(`LAYOUT`); selector 15 is an escape: the next word is one value as it is, for values of over 60 bits.  The coder
takes the densest selector that fits what follows.

A token store is a folder of Parquet rows, one a block: shard (shards follow doc_id order), block (in order in the
shard), ids_before (ids of the shard before this block), n_ids, doc_ids, sizes (tokens of every document) and words.
Blocks hold whole documents and are sized in ids, so one reader decodes any block with vectorised shifts and finds
any document by the running sum of `sizes`.

Texts are encoded by the tokenizers library, every distinct piece once.  Null and empty texts hold the end id only.
Equal doc_ids stay together in one shard, each row written by itself; null doc_ids come first.  Only doc_id and text
are read, so no other column can clash.  An empty table gives an empty store.
"""

from __future__ import annotations

import gc
import uuid
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.llm.bpe import tokenizer
from erasureml.llm.core import LOWER, NO_ID, Texts, few_rows, read_table, shared_folder, shuffle_parts
from erasureml.llm.pieces import BLANK, CLASS, DIGIT, LETTER, DistinctCoder, gather

END_ID = 2
BLOCK_IDS = 1 << 18
TASK_CHARS = 1_000_000
SEGMENT = 1 << 15
WORD_END = "</w>"
# Fixed values: (ids in a word, bits of each) by selector.
LAYOUT = ((60, 1), (30, 2), (20, 3), (15, 4), (12, 5), (10, 6), (8, 7), (7, 8), (6, 10), (5, 12), (4, 15), (3, 20), (2, 30), (1, 60))
ESCAPE = 15
STORE = "shard int, block int, ids_before long, n_ids long, doc_ids binary, sizes binary, words binary"


def s8b_encode(values: np.ndarray) -> np.ndarray:
    """uint64 values to Simple-8b words."""
    v = np.ascontiguousarray(values, np.uint64)
    cuts = range(0, len(v), SEGMENT)  # the arrays stay in the cache
    return np.concatenate([np.zeros(0, np.uint64), *(_segment(v[i : i + SEGMENT], i + SEGMENT >= len(v)) for i in cuts)])


_LENGTHS = np.array([i.bit_length() for i in range(1 << 16)], np.uint8)


def bit_lengths(v: np.ndarray) -> np.ndarray:
    out = _LENGTHS[v & np.uint64(0xFFFF)]
    for shift in (16, 32, 48):
        high = v >> np.uint64(shift)
        if not high.any():
            break
        part = _LENGTHS[high & np.uint64(0xFFFF)]
        out = np.where(part > 0, part + np.uint8(shift), out)
    return out


def _segment(v: np.ndarray, last: bool) -> np.ndarray:
    """Words of a segment; only the last word of the last segment may lack values."""
    n = len(v)
    here = np.arange(n, dtype=np.int32)
    choice, step = np.full(n, ESCAPE, np.uint8), np.ones(n, np.int32)
    width = bit_lengths(v)
    top = int(width.max())
    for s in reversed(range(len(LAYOUT))):  # denser selectors overwrite
        count, bits = LAYOUT[s]
        bad = np.flatnonzero(width > bits) if top > bits else np.zeros(0, np.int64)
        runs = np.diff(np.concatenate([[-1], bad, [n]]))  # 1 more than the fitting values before each misfit, and at the end
        if runs[:-1].max(initial=0) <= count and runs[-1] == 1:
            continue
        until = np.repeat(np.append(bad, n).astype(np.int32), np.append(runs[:-1], runs[-1] - 1))
        fits = until - here >= (np.minimum(count, n - here) if last else count)
        choice[fits], step[fits] = s, count
    jump, at, starts = (here + step).tolist(), 0, []
    while at < n:
        starts.append(at)
        at = jump[at]
    starts_a = np.array(starts)
    kinds = choice[starts_a]
    place = np.cumsum(1 + (kinds == ESCAPE)) - 1 - (kinds == ESCAPE)
    out = np.zeros(int(place[-1]) + 1 + int(kinds[-1] == ESCAPE), np.uint64)
    padded = np.concatenate([v, np.zeros(LAYOUT[0][0], np.uint64)])
    for s, (count, bits) in enumerate(LAYOUT):
        own = np.flatnonzero(kinds == s)
        if len(own):
            word = np.full(len(own), s, np.uint64)
            for k in range(count):
                i = starts_a[own] + k
                word |= np.where(i < n, padded[i], np.uint64(0)) << np.uint64(4 + k * bits)
            out[place[own]] = word
    own = np.flatnonzero(kinds == ESCAPE)
    out[place[own]], out[place[own] + 1] = ESCAPE, v[starts_a[own]]
    return out


def s8b_decode(words: np.ndarray, n: int) -> np.ndarray:
    """The first n values."""
    if not n:
        return np.zeros(0, np.uint64)
    w = np.ascontiguousarray(words, np.uint64)
    kinds = (w & np.uint64(15)).astype(np.int64)
    raw = np.zeros(len(w), bool)
    if (kinds == ESCAPE).any():
        at = 0
        for e in np.flatnonzero(kinds == ESCAPE).tolist():  # a raw word may look like an escape itself
            if e >= at:
                raw[e + 1], at = True, e + 2
    counts = np.array([c for c, _ in LAYOUT] + [0, 1])[kinds]
    counts[raw] = 0
    first = np.cumsum(counts) - counts
    out = np.zeros(int(counts.sum()), np.uint64)
    for s, (count, bits) in enumerate(LAYOUT):
        own = np.flatnonzero((kinds == s) & ~raw)
        for k in range(count if len(own) else 0):
            out[first[own] + k] = (w[own] >> np.uint64(4 + k * bits)) & np.uint64((1 << bits) - 1)
    own = np.flatnonzero((kinds == ESCAPE) & ~raw)
    out[first[own]] = w[own + 1]
    return out[:n]


class PieceCoder(DistinctCoder):
    """Pieces of a vocabulary that lower-cases and drops white space: runs of letters, single digits, runs of marks.

    Words go through the library many to a call, their ids parted at the tokens that end a word.
    """

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer, pre_tokenizers

        super().__init__(tokenizer(path, False))  # a special token's string in a text is that token, as in the library's plain call
        self.special = tuple(t.content.encode() for t in self.full.get_added_tokens_decoder().values())
        self.light = Tokenizer(self.full.model)
        self.light.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        vocabulary = self.full.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for x, i in vocabulary.items() if x.endswith(WORD_END)]] = True

    def part(self, texts: Texts, data: np.ndarray, lead: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        data = LOWER[data] + np.where(lead & (data < 0x9F), np.uint8(0x20), np.uint8(0))
        kind = CLASS[data]
        first = np.zeros(len(data) + 1, bool)
        first[texts.starts] = True
        cut = first[:-1] | np.concatenate([[True], kind[1:] != kind[:-1]])[: len(kind)] | (kind == DIGIT)
        bounds = np.append(np.flatnonzero(cut), len(data))
        use = kind[bounds[:-1]] != BLANK
        return data, bounds[:-1][use], bounds[1:][use]

    def made(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        letters = np.array([CLASS[p[0]] == LETTER for p in pieces], bool)
        words = [p.decode() for p, x in zip(pieces, letters.tolist(), strict=True) if x]
        a, b = self._words(words), self.singly([p for p, x in zip(pieces, letters.tolist(), strict=True) if not x])
        lens = np.empty(len(pieces), np.int64)
        lens[letters], lens[~letters] = a[1], b[1]
        first = np.empty(len(pieces), np.int64)
        first[letters], first[~letters] = np.cumsum(a[1]) - a[1], len(a[0]) + np.cumsum(b[1]) - b[1]
        return np.concatenate([a[0], b[0]])[gather(first, lens)], lens

    def _words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        ids = [np.zeros(0, np.uint32)]
        for i in range(0, len(words), 10_000):
            part = words[i : i + 10_000]
            lines = [" ".join(part[j : j + 100]) for j in range(0, len(part), 100)]
            ids += [np.array(e.ids, np.uint32) for e in self.light.encode_batch_fast(lines, add_special_tokens=False)]
        flat = np.concatenate(ids)
        ends = np.flatnonzero(self.ends[flat]) + 1
        if len(ends) != len(words):
            raise ValueError("a word doesn't end with a word-end token")
        return flat, np.diff(ends, prepend=0)


@lru_cache(maxsize=2)
def piece_coder(path: str) -> PieceCoder:
    """Kept by a Python worker from task to task."""
    return PieceCoder(path)


def write_store(docs: DataFrame, path: str, vocabulary: str, end_id: int = END_ID, block_ids: int = BLOCK_IDS) -> None:
    """Encode doc_id, text in ascending doc_id order into a token store at `path`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gc.disable()  # reference counts free all that a task makes; the collector would walk the kept pieces again and again
        try:
            yield from blocks_of(batches)
        finally:
            gc.enable()

    def blocks_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, coder = TaskContext.get().partitionId(), piece_coder(vocabulary)
        block = before = held = 0
        docs_, sizes_, ids_ = [], [], []

        def flush() -> pa.RecordBatch:
            nonlocal block, before, held
            ids, sizes = np.concatenate(ids_), np.concatenate(sizes_)
            row = {"shard": pa.array([shard], pa.int32()), "block": pa.array([block], pa.int32()), "ids_before": pa.array([before], pa.int64()), "n_ids": pa.array([len(ids)], pa.int64())}
            row |= {k: pa.array([x.tobytes()], pa.binary()) for k, x in (("doc_ids", np.concatenate(docs_)), ("sizes", s8b_encode(sizes)), ("words", s8b_encode(ids)))}
            block, before, held = block + 1, before + len(ids), 0
            docs_.clear(), sizes_.clear(), ids_.clear()
            return pa.RecordBatch.from_pydict(row)

        for batch in batches:
            keys = pc.fill_null(batch.column(0), int(NO_ID)).to_numpy(zero_copy_only=False)
            total, lo = np.cumsum(pc.fill_null(pc.utf8_length(batch.column(1)), 0).to_numpy(zero_copy_only=False)), 0
            while lo < batch.num_rows:
                hi = max(lo + 1, int(np.searchsorted(total, (total[lo - 1] if lo else 0) + TASK_CHARS)))
                ids, sizes = coder.encode(batch.column(1).slice(lo, hi - lo))
                ends = np.cumsum(sizes)
                ids_.append(np.insert(ids, ends, end_id)), sizes_.append(sizes + 1), docs_.append(keys[lo:hi])
                held, lo = held + int(ends[-1]) + hi - lo, hi
                if held >= block_ids:
                    yield flush()
        if docs_:
            yield flush()

    parts = shuffle_parts(docs.sparkSession)
    ordered = few_rows(docs).select(F.col("doc_id").cast("long"), "text").repartitionByRange(parts, "doc_id").sortWithinPartitions("doc_id")
    ordered.mapInArrow(run, STORE).write.option("compression", "none").parquet(path)


def read_store(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids as packed little-endian 32-bit integers) of every document."""
    return _decoded(spark, path, "ids binary", lambda ids: [i.tobytes() for i in ids], pa.binary())


def checksums(spark: SparkSession, path: str) -> DataFrame:
    return _decoded(spark, path, "ids_crc32 long", lambda ids: [zlib.crc32(i.tobytes()) for i in ids], pa.int64())


def _decoded(spark: SparkSession, path: str, column: str, last, kind: pa.DataType) -> DataFrame:
    store = spark.read.schema(STORE).parquet(path)
    # one row a shard, and there are as many shards as shuffle partitions: a bound that doesn't grow with the data
    sums = {r["shard"]: r["n"] for r in store.groupBy("shard").agg(F.sum("n_ids").alias("n")).collect()}
    order = sorted(sums)
    offset = dict(zip(order, np.concatenate([[0], np.cumsum([sums[s] for s in order])]).tolist(), strict=False))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                keys = np.frombuffer(row["doc_ids"], np.int64)
                sizes = s8b_decode(np.frombuffer(row["sizes"], np.uint64), len(keys)).astype(np.int64)
                ids = s8b_decode(np.frombuffer(row["words"], np.uint64), row["n_ids"]).astype("<u4")
                ends = np.cumsum(sizes)
                starts = offset[row["shard"]] + row["ids_before"] + ends - sizes
                found = [None if k == NO_ID else k for k in keys.tolist()]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(found, pa.int64()), pa.array(starts), pa.array(sizes), pa.array(last(np.split(ids, ends[:-1])), kind)], ["doc_id", "start", "n_tokens", column.split()[0]]
                )

    return store.mapInArrow(run, f"doc_id long, start long, n_tokens long, {column}")


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new folder in the shared checkpoint folder."""
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op7_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = fresh_path(spark, "tokens")
    write_store(read_table(spark, sf_dir, "documents"), path, default_vocabulary())
    return checksums(spark, path)
