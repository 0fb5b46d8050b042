"""Shared machinery: blocks of whole texts, vectorised tokens and hashes, and a distributed hash lookup.

Texts are grouped into *blocks* of a few MB, kept compressed in reliable (shared) checkpoint storage.  Operators
that need a statistic of the whole corpus for a hash (a count, the smallest document) send every block's
*distinct* hashes, range-partitioned and packed, to reducers and get the answers back in the same order.  As each
block sends a hash once, a key that a third of all rows hold costs one entry a block, wherever it is reduced.
"""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import hashlib
import shutil
import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BLOCK_BYTES = 8 << 20
CHUNK_BYTES = 1 << 20
NO_ID = np.iinfo(np.int64).min
BLOCK_SCHEMA = "block_id long, doc_ids binary, lens binary, body binary"
_MASK = (1 << 64) - 1


# ---------------------------------------------------------------- session


BATCH_ROWS, BATCH_BYTES = 512, 8 << 20


def few_rows(df: DataFrame) -> DataFrame:
    """df itself; from here on the session sends Python at most BATCH_ROWS rows or about BATCH_BYTES at once, as rows hold whole
    texts.  (The plan reads both settings when it runs, which is after this returns, so they can't be put back here.)"""
    conf = df.sparkSession.conf
    for name, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        name = f"spark.sql.execution.arrow.{name}"
        now = (conf.get(name, None) or "").removesuffix("b")
        if not (now.isdigit() and 0 < int(now) <= most):
            conf.set(name, str(most))
    return df


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return few_rows(spark.read.parquet(f"{sf_dir}/{name}.parquet"))


def shuffle_parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the session names.  Without one, a temporary folder if Spark runs in one JVM; on a
    cluster that would be a folder of the driver's own, so there it is an error."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(named or _own_folder())
    return sc.getCheckpointDir()


def _own_folder() -> str:
    """Of this process; it goes when the process ends."""
    path = tempfile.mkdtemp(prefix="ckpt")
    atexit.register(shutil.rmtree, path, True)
    return path


def reliable(df: DataFrame, dealt: bool = False) -> DataFrame:
    """Materialise in the shared checkpoint folder, so that a lost executor costs nothing twice.

    dealt: keep how the result is dealt, so that joins on the same key don't move it again. An adaptive plan doesn't
    tell, so this one is planned without.
    """
    conf, name = df.sparkSession.conf, "spark.sql.adaptive.enabled"
    shared_folder(df.sparkSession)
    if not dealt:
        return df.checkpoint(eager=True)
    before = conf.get(name)
    conf.set(name, "false")
    try:
        return df.select("*").checkpoint(eager=True)
    finally:
        conf.set(name, before)


def give_back() -> None:
    """Hand freed memory back to the system, as a Python worker outlives its task and the next one runs in the JVM beside it."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


# ---------------------------------------------------------------- packing


def squeeze(data: bytes) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(data)


def expand(data: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(data)


def pack(*arrays: np.ndarray) -> bytes:
    """Integer arrays as byte planes, compressed; a sorted first array is best, as it is kept as differences."""
    out = [np.array([len(arrays), *map(len, arrays)], np.int64).tobytes()]
    for k, a in enumerate(arrays):
        a = np.ascontiguousarray(a).astype(np.int64, copy=False) if a.dtype != np.uint64 else a.view(np.int64)
        if k == 0 and len(a):
            a = np.diff(a, prepend=np.int64(0))
        out.append(np.ascontiguousarray(a.view(np.uint8).reshape(-1, 8).T).tobytes())
    return squeeze(b"".join(out))


def unpack(data: bytes) -> list[np.ndarray]:
    raw = np.frombuffer(expand(data), np.uint8)
    k = int(raw[:8].view(np.int64)[0])
    sizes, at, out = raw[8 : 8 + 8 * k].view(np.int64), 8 + 8 * k, []
    for j, n in enumerate(map(int, sizes)):
        a = np.ascontiguousarray(raw[at : at + 8 * n].reshape(8, n).T).reshape(-1).view(np.int64)
        out.append(np.cumsum(a) if j == 0 else a)
        at += 8 * n
    return out


# ---------------------------------------------------------------- blocks


def text_blocks(docs: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(doc_id, text) as checkpointed blocks. A null text is empty; a null doc_id is kept (as NO_ID inside)."""

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, seq = TaskContext.get().partitionId() << 32, 0
        ids: list[np.ndarray] = []
        lens: list[np.ndarray] = []
        body: list[bytes] = []
        size = 0

        def flush() -> pa.RecordBatch:
            nonlocal seq, size
            row = pa.RecordBatch.from_pydict(
                {
                    "block_id": pa.array([base + seq], pa.int64()),
                    "doc_ids": pa.array([np.concatenate(ids).tobytes()], pa.binary()),
                    "lens": pa.array([np.concatenate(lens).tobytes()], pa.binary()),
                    "body": pa.array([squeeze(b"".join(body))], pa.binary()),
                }
            )
            ids.clear(), lens.clear(), body.clear()
            seq, size = seq + 1, 0
            return row

        for batch in batches:
            key = pc.fill_null(batch.column(0).cast(pa.int64()), int(NO_ID)).to_numpy(zero_copy_only=False)
            text = pc.fill_null(batch.column(1), "").cast(pa.large_binary())
            off = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1]
            data = memoryview(text.buffers()[2] or b"")
            i = 0
            while i < len(key):
                j = int(np.searchsorted(off, off[i] + max(1, block_bytes - size), side="left"))
                j = min(max(j, i + 1), len(key))
                ids.append(key[i:j]), lens.append(np.diff(off[i : j + 1]))
                body.append(bytes(data[off[i] : off[j]]))
                size, i = size + int(off[j] - off[i]), j
                if size >= block_bytes:
                    yield flush()
        if ids:
            yield flush()

    return reliable(few_rows(docs).select("doc_id", "text").mapInArrow(build, BLOCK_SCHEMA).repartition(shuffle_parts(docs.sparkSession), "block_id"), dealt=True)


class Texts:
    """UTF-8 texts end to end: lens, starts (byte offsets) and the bytes."""

    def __init__(self, lens: np.ndarray, body: bytes) -> None:
        self.lens, self.body = lens, body
        self.starts = np.concatenate([[0], np.cumsum(lens)]).astype(np.int64)

    @classmethod
    def of(cls, column: pa.Array) -> Texts:
        text = pc.fill_null(column, "").cast(pa.large_binary())
        off = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1]
        return cls(np.diff(off), bytes(memoryview(text.buffers()[2] or b"")[off[0] : off[-1]]))

    def text(self, i: int) -> bytes:
        return self.body[self.starts[i] : self.starts[i + 1]]

    def chunks(self, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
        """Ranges of whole documents of about `limit` bytes."""
        i, n = 0, len(self.lens)
        while i < n:
            j = int(np.searchsorted(self.starts, self.starts[i] + limit, side="right")) - 1
            j = min(max(j, i + 1), n)
            yield i, j
            i = j


class Block(Texts):
    """One block opened in a task, with its doc_ids; row has the answers."""

    def __init__(self, row) -> None:
        super().__init__(np.frombuffer(row.lens, np.int64), expand(row.body))
        self.block_id = int(row.block_id)
        self.doc_ids = np.frombuffer(row.doc_ids, np.int64)
        self.row = row

    def ids_out(self) -> pd.array:
        return pd.array([pd.NA if x == NO_ID else int(x) for x in self.doc_ids], "Int64")


# ---------------------------------------------------------------- hashing


def _stream(seed: int, n: int) -> np.ndarray:
    """n words of the splitmix64 sequence."""
    with np.errstate(over="ignore"):
        z = np.uint64(seed) + np.uint64(0x9E3779B97F4A7C15) * np.arange(1, n + 1, dtype=np.uint64)
        return mix(z)


def mix(z: np.ndarray) -> np.ndarray:
    """The splitmix64 finaliser."""
    with np.errstate(over="ignore"):
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return z ^ (z >> np.uint64(31))


class Roller:
    """Values of byte ranges from prefix sums of randomised byte values times inverse powers of an odd base (mod 2^64).

    Cheap at every position, but structured texts can share a value: for proposing places to look at, never for
    identity. `range_hash` is for that.
    """

    def __init__(self, seed: int) -> None:
        self.table = _stream(seed, 256) | np.uint64(1)
        self.base = int(_stream(seed + 77, 1)[0]) | 1
        self.inverse = pow(self.base, -1, 1 << 64)
        self._up = self._down = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self._up) >= n:
            return
        up, down = np.full(n, self.base, np.uint64), np.full(n, self.inverse, np.uint64)
        up[0] = down[0] = 1
        self._up, self._down = np.multiply.accumulate(up), np.multiply.accumulate(down)

    def prefix(self, data: np.ndarray) -> np.ndarray:
        n = len(data)
        self._powers(n + 1)
        out = np.zeros(n + 1, np.uint64)
        np.cumsum(self.table[data] * self._down[:n], out=out[1:])
        return out

    def ranges(self, prefix: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        return mix((prefix[hi] - prefix[lo]) * self._up[lo])


LANE_BYTES = 64
_LOW = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
_KEYS = _stream(20011, 6)


def lanes_of(data: np.ndarray) -> np.ndarray:
    """The eight bytes from every place on, as one little-endian word; zero beyond the end."""
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    return np.ndarray(len(data) + 1, "<u8", padded, strides=(1,))


def range_hash(data: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two independent 64-bit hashes of the bytes in every [lo, hi): 128 bits that identify a string.

    Eight bytes at a time go into each state, which is mixed by a permutation of all its bits before the next; ranges
    over LANE_BYTES take a keyed BLAKE2b digest.  For one length of up to eight bytes the first hash can't collide at all.
    """
    n = hi - lo
    lanes = lanes_of(data)
    with np.errstate(over="ignore"):
        one, two = mix(n.astype(np.uint64) * _KEYS[0] + _KEYS[1]), mix(n.astype(np.uint64) * _KEYS[2] + _KEYS[3])
        short = n <= LANE_BYTES
        live, at, left = np.flatnonzero(short & (n > 0)), None, None
        for k in range(0, LANE_BYTES, 8):
            live = live[n[live] > k] if k else live
            if not len(live):
                break
            at, left = lo[live] + k, np.minimum(n[live] - k, 8)
            v = lanes[at] & _LOW[left]
            one[live] = mix(one[live] ^ v)
            two[live] = mix((two[live] + v) * (_KEYS[4] | np.uint64(1)) ^ _KEYS[5])
    long = np.flatnonzero(~short)
    if len(long):
        body = data.tobytes()
        got = b"".join([hashlib.blake2b(body[i:j], digest_size=16, key=b"range").digest() for i, j in zip(lo[long].tolist(), hi[long].tolist(), strict=True)])
        pair = np.frombuffer(got, np.uint64).reshape(-1, 2)
        one[long], two[long] = pair[:, 0], pair[:, 1]
    return one, two


#: Bytes between words: space and 9 to 13.
SEPARATORS = np.zeros(256, bool)
SEPARATORS[[32, 9, 10, 11, 12, 13]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


class Words:
    """The words of documents i..j of a block: `hash` and `check` (128 bits that identify a word together), byte range
    [`lo`, `hi`) in the chunk, and `ends` by document."""

    def __init__(self, block: Texts, i: int, j: int, lower: bool = False, separators: np.ndarray = SEPARATORS) -> None:
        first = int(block.starts[i])
        raw = np.frombuffer(block.body, np.uint8, int(block.starts[j]) - first, first)
        data = LOWER[raw] if lower else raw
        gap = separators[data]
        edge = np.zeros(len(data) + 1, bool)  # a document's start also parts words
        edge[block.starts[i : j + 1] - first] = True
        opens = ~gap & (edge[:-1] | np.concatenate([[True], gap[:-1]]))
        closes = ~gap & (edge[1:] | np.concatenate([gap[1:], [True]]))
        self.lo, self.hi = np.flatnonzero(opens), np.flatnonzero(closes) + 1
        self.hash, self.check = range_hash(data, self.lo, self.hi)
        self.ends = np.searchsorted(self.lo, block.starts[i + 1 : j + 1] - first)
        self.counts = np.diff(self.ends, prepend=0)
        self.raw = raw


def ngram_hash(words: np.ndarray, n: int, seed: int = 0, at: np.ndarray | None = None) -> np.ndarray:
    """Hash of every n consecutive word hashes (or of those from `at` on); positions that lack n words are left out."""
    m = max(0, len(words) - n + 1)
    coef = _stream(9176 + 131 * n + seed, n) | np.uint64(1)
    out = np.zeros(m if at is None else len(at), np.uint64)
    with np.errstate(over="ignore"):
        for k in range(n):
            out += mix((words[k : k + m] if at is None else words[at + k]) ^ coef[k]) * coef[k]
    return mix(out)


def starts_of(ends: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], ends[:-1]]).astype(np.int64)


def complete(ends: np.ndarray, n: int, total: int) -> np.ndarray:
    """Which of the total-n+1 positions have all n items in one document."""
    m = max(0, total - n + 1)
    last = np.repeat(ends, np.diff(ends, prepend=0))[:m]
    return np.arange(m) + n <= last


# ---------------------------------------------------------------- lookup


def distinct(hashes: np.ndarray, check: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct hashes, an order that sorts (equal ones in any order), and where each run starts.

    check: the rest of a wide hash; entries are equal if both are, and one hash may then start several runs.
    """
    order = np.argsort(hashes)
    h = hashes[order]
    new = np.concatenate([[True], h[1:] != h[:-1]]) if len(h) else np.zeros(0, bool)
    if check is not None and len(h):
        c = check[order]
        apart = np.concatenate([[True], c[1:] != c[:-1]])
        if (apart & ~new).any():  # some hash stands for two strings
            order = np.lexsort((check, hashes))
            h, c = hashes[order], check[order]
            new = np.concatenate([[True], (h[1:] != h[:-1]) | (c[1:] != c[:-1])])
    at = np.flatnonzero(new)
    return h[at], order, at


def run_of(order: np.ndarray, at: np.ndarray) -> np.ndarray:
    """For every hash, the place of its run among the distinct ones."""
    out = np.empty(len(order), np.int64)
    out[order] = np.repeat(np.arange(len(at)), np.diff(np.append(at, len(order))))
    return out


def _cuts(hashes: np.ndarray, parts: int) -> np.ndarray:
    bounds = np.array([(p << 64) // parts for p in range(1, parts)], dtype=object).astype(np.uint64) if parts > 1 else np.zeros(0, np.uint64)
    return np.concatenate([[0], np.searchsorted(hashes, bounds), [len(hashes)]])


def each_block(df: DataFrame, work: Callable[[Block], Iterator[pd.DataFrame]], schema: str) -> DataFrame:
    """work(block) for every row of blocks, in bounded memory: a block at a time."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for row in frame.itertuples(index=False):
                yield from work(Block(row))

    return df.mapInPandas(run, schema)


TALLY = -1


def answers(blocks: DataFrame, question: Callable[[Block], tuple[np.ndarray, list[np.ndarray]]], merge: Callable, tally: Callable | None = None, wide: bool = False) -> DataFrame:
    """The corpus-wide answer for each distinct hash of every block: (block_id, answers), kept reliably.

    question(block) gives sorted distinct hashes and value arrays of the same length.  merge(values, at) gets the
    values of all blocks for one hash range, sorted by hash, and where the runs of equal hashes start; it returns
    arrays with an entry for every value (see `spread`).  `attach` adds the answers to the blocks, `answer_of` reads
    them.  tally(values, at) may give integers to be summed over all hash ranges; read them with `tally_of`.
    wide: the first of the question's arrays is the rest of the hash (see `distinct`) and isn't handed to merge.
    """
    parts = shuffle_parts(blocks.sparkSession)

    def send(block: Block) -> Iterator[pd.DataFrame]:
        hashes, values = question(block)
        cuts = _cuts(hashes, parts)
        full = [p for p in range(parts) if cuts[p + 1] > cuts[p]]
        yield pd.DataFrame(
            {
                "block_id": np.full(len(full), block.block_id, np.int64),
                "part": np.array(full, np.int32),
                "load": [pack(hashes[cuts[p] : cuts[p + 1]], *(v[cuts[p] : cuts[p + 1]] for v in values)) for p in full],
            }
        )

    def reduce(frame: pd.DataFrame) -> pd.DataFrame:
        got = [unpack(x) for x in frame["load"]]
        hashes = np.concatenate([g[0] for g in got]).view(np.uint64)
        _, order, at = distinct(hashes, np.concatenate([g[1] for g in got]) if wide else None)
        values = [np.concatenate(v)[order] for v in zip(*(g[1 + wide :] for g in got), strict=True)]
        cuts = np.cumsum([len(g[0]) for g in got])[:-1]
        split = []
        for answer in merge(values, at):
            rows = np.empty(len(order), np.int64)
            rows[order] = answer
            split.append(np.split(rows, cuts))
        out = pd.DataFrame({"block_id": frame["block_id"], "part": frame["part"], "answer": [pack(np.zeros(0, np.int64), *a) for a in zip(*split, strict=True)]})
        if tally:
            row = pd.DataFrame({"block_id": [TALLY], "part": frame["part"][:1].to_list(), "answer": [pack(np.zeros(0, np.int64), np.array(tally(values, at), np.int64))]})
            out = pd.concat([out, row], ignore_index=True)
        return out

    asked = each_block(blocks, send, "block_id long, part int, load binary")
    told = asked.groupBy("part").applyInPandas(reduce, "block_id long, part int, answer binary")
    return reliable(told.groupBy("block_id").agg(F.collect_list(F.struct("part", "answer")).alias("answers")), dealt=True)


def attach(blocks: DataFrame, held: DataFrame, name: str) -> DataFrame:
    return blocks.join(held.withColumnRenamed("answers", name).hint("shuffle_hash"), "block_id", "left")


def spread(x: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    """A value of every run to its members."""
    return np.repeat(x, np.diff(np.append(at, n)))


def answer_of(row, name: str, k: int = 0) -> np.ndarray:
    got = getattr(row, name)
    if got is None or len(got) == 0:
        return np.zeros(0, np.int64)
    return np.concatenate([unpack(x["answer"])[1 + k] for x in sorted(got, key=lambda x: x["part"])])


def tally_of(held: DataFrame, size: int) -> list[int]:
    """One row with an entry for every hash range, of which there are as many as shuffle partitions."""
    row = held.where(F.col("block_id") == TALLY).first()
    total = np.zeros(size, np.int64)
    for x in row["answers"] if row else []:
        total += unpack(bytes(x["answer"]))[1]
    return total.tolist()
