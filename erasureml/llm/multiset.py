"""Homomorphic multiset fingerprints of documents.

A document is the multiset of its paragraphs (lines that aren't empty) and its line ends.  A paragraph is hashed to a
wide vector; the fingerprint is the sum of the vectors, each lane modulo a power of two.  So the order of
paragraphs doesn't matter, and inserting or deleting one adds or subtracts its vector (`add`, `subtract`).

A vector has `STRONG` lanes modulo 2^64, the words of a keyed 256-bit BLAKE2b digest of the whole paragraph, for
equality, and LEVELS x LANES lanes modulo 2^8, to which the paragraph's runs of three words add (the words, if it has
fewer than three), for likeness.  Level l takes only hashes that begin with 2 l zero bits, a quarter of those of the level
before; the last one is sparse for texts of some 2 GB, more than a row can hold, so whatever a document's length, some
level has few enough entries that most lanes hold one.  The likeness of two fingerprints is the share of equal lanes
among those used by either, at the first level that is at most `FULL` used; equal fingerprints have likeness 1.

Null and empty texts are the empty multiset (zero), alike only to each other.  Of rows with equal doc_ids the next one in
order of text counts as the next document; exact repeats are rows of their own.  Only doc_id and text are read, so
no other column can clash.  An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.llm.bpe import slices
from erasureml.llm.core import NO_ID, Texts, Words, complete, mix, ngram_hash, few_rows, read_table, shuffle_parts

STRONG, LEVELS, LANES, RUN = 4, 12, 64, 3
FULL = 0.75
WIDTH = 8 * STRONG + LEVELS * LANES
_SALT = mix(np.arange(1, 2, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def wide(paragraph: bytes) -> bytes:
    return hashlib.blake2b(paragraph, digest_size=8 * STRONG, key=b"paragraph").digest()


_END = np.frombuffer(wide(b"\n"), np.uint64)  # no paragraph holds a line end


def vectors(texts: list[str | None]) -> np.ndarray:
    """A fingerprint (WIDTH bytes) of every text."""
    whole = Texts.of(pa.array([t or "" for t in texts], pa.string()))
    n, data = len(texts), np.frombuffer(whole.body, np.uint8)
    cuts = np.unique(np.concatenate([whole.starts, np.flatnonzero(data == 10) + 1]))
    if len(cuts) < 2:
        return np.zeros((n, WIDTH), np.uint8)
    lines = Texts(np.diff(cuts), whole.body)
    lo, hi = cuts[:-1], cuts[1:]
    doc = np.searchsorted(whole.starts, lo, "right") - 1
    ended = data[hi - 1] == 10
    said = np.flatnonzero(hi - ended > lo)
    body = whole.body
    digests = np.frombuffer(b"".join([wide(body[i:j]) for i, j in zip(lo[said].tolist(), (hi - ended)[said].tolist(), strict=True)]), np.uint64).reshape(-1, STRONG)
    strong = np.zeros((n, STRONG), np.uint64)
    for k in range(STRONG):
        value = np.where(ended, _END[k], np.uint64(0))
        value[said] += digests[:, k]
        np.add.at(strong[:, k], doc, value)
    words = Words(lines, 0, len(lo))
    line = np.repeat(np.arange(len(lo)), words.counts)
    ok = complete(words.ends, RUN, len(words.hash))
    short = words.counts[line] < RUN
    e = np.concatenate([ngram_hash(words.hash, RUN)[ok], mix(words.hash[short] ^ _SALT[-1])])
    at = np.concatenate([doc[line[: len(ok)][ok]], doc[line[short]]])
    lane, value = (e & np.uint64(LANES - 1)).astype(np.int64), (mix(e) & np.uint64(255)).astype(np.float64)
    soft = np.zeros((n, LEVELS, LANES), np.uint8)
    for level in range(LEVELS):
        if level:
            keep = e >> np.uint64(64 - 2 * level) == 0
            e, at, lane, value = e[keep], at[keep], lane[keep], value[keep]
        total = np.bincount(at * LANES + lane, value, minlength=n * LANES)
        soft[:, level] = (total.astype(np.int64) & 255).astype(np.uint8).reshape(n, LANES)
    return np.concatenate([strong.view(np.uint8).reshape(n, 8 * STRONG), soft.reshape(n, -1)], 1)


def add(a: np.ndarray, b: np.ndarray, sign: int = 1) -> np.ndarray:
    """The fingerprint of the union of two multisets (sign -1: of what is left of the first without the second)."""
    a, b = np.ascontiguousarray(a), np.ascontiguousarray(b)
    wide = np.uint64(sign & (1 << 64) - 1)
    strong = a[..., : 8 * STRONG].copy().view(np.uint64) + wide * b[..., : 8 * STRONG].copy().view(np.uint64)
    return np.concatenate([strong.view(np.uint8), a[..., 8 * STRONG :] + np.uint8(sign & 255) * b[..., 8 * STRONG :]], -1)


def subtract(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return add(a, b, -1)


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row, from 0 to 1."""
    x, y = (v[:, 8 * STRONG :].reshape(-1, LEVELS, LANES) for v in (a, b))
    used = ((x > 0) | (y > 0)).sum(2)
    fits = (used <= FULL * LANES) & (used > 0)
    level = np.where(fits.any(1), fits.argmax(1), np.where(used.any(1), LEVELS - 1, 0))
    rows = np.arange(len(a))
    alike = ((x == y) & (x > 0)).sum(2)[rows, level] / np.maximum(used[rows, level], 1)
    return np.where((a == b).all(1), 1.0, alike)


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint binary)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for lo, hi in slices(texts):
                yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0).slice(lo, hi - lo).cast(pa.int64()), "fingerprint": pa.array([v.tobytes() for v in vectors(texts[lo:hi])], pa.binary())})

    return few_rows(docs).select("doc_id", "text").mapInArrow(run, "doc_id long, fingerprint binary")


def updated(prints: DataFrame, changes: DataFrame) -> DataFrame:
    """Fingerprints after changes (doc_id, paragraph, inserted boolean), without reading the other paragraphs.

    A paragraph is taken without a line end.
    """

    def delta(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            v = vectors(batch.column(1).to_pylist())
            v = np.where(np.array(batch.column(2).to_pylist(), bool)[:, None], v, subtract(np.zeros_like(v), v)) if len(v) else v
            yield pa.RecordBatch.from_pydict({"id": batch.column(0).cast(pa.int64()), "v": pa.array([x.tobytes() for x in v], pa.binary())})

    def applied(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for own, moves in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                v = np.frombuffer(own, np.uint8)
                for m in moves or ():
                    v = add(v, np.frombuffer(m, np.uint8))
                out.append(v.tobytes())
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0), "fingerprint": pa.array(out, pa.binary())})

    moved = changes.select("doc_id", "paragraph", "inserted").mapInArrow(delta, "id long, v binary")
    moves = moved.groupBy("id").agg(F.collect_list("v").alias("moves"))  # as many as one document's changes
    return prints.join(moves, F.col("doc_id") == F.col("id"), "left").select("doc_id", "fingerprint", "moves").mapInArrow(applied, "doc_id long, fingerprint binary")


def with_next(docs: DataFrame) -> DataFrame:
    """docs dealt so that every partition has whole stretches of ascending doc_id, each followed by the row after it.

    Stretches are parted at quantiles of doc_id; the first row of a stretch goes to the stretch before it too (_copy),
    and the first of all to the last.  Equal ids are in order of their text.
    """
    parts = shuffle_parts(docs.sparkSession)
    keyed = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(int(NO_ID))).alias("key"), F.coalesce("text", F.lit("")).alias("text"))
    cuts = sorted({int(x) for x in keyed.approxQuantile("key", [k / parts for k in range(1, parts)], 0.25 / parts)}) if parts > 1 else []
    width = max(1, int(len(cuts) ** 0.5))
    rows = [cuts[i : i + width] for i in range(0, len(cuts), width)]

    def below(values: list[int]) -> str:
        return f"size(filter(array({', '.join(f'{v}L' if v > NO_ID else 'bigint(' + chr(39) + str(v) + chr(39) + ')' for v in values)}), c -> c <= key))"

    # two steps of about the square root of the number of cuts each
    coarse = below([r[0] for r in rows]) if rows else "0"
    fine = "case _row " + " ".join(f"when {i + 1} then {i * width} + {below(r)}" for i, r in enumerate(rows)) + " else 0 end" if rows else "0"
    placed = keyed.withColumn("_row", F.expr(coarse)).withColumn("part", F.expr(fine)).drop("_row")
    heads = sorted((r["head"], r["part"]) for r in placed.groupBy("part").agg(F.min("key").alias("head")).collect())  # a row a stretch
    before = {heads[i][0]: heads[i - 1][1] for i in range(len(heads))}
    copies = placed.limit(0)
    if before:
        table = docs.sparkSession.createDataFrame(list(before.items()), "key long, part int")
        copies = placed.drop("part").join(F.broadcast(table), "key").select("key", "text", "part")
    dealt = placed.withColumn("copy", F.lit(0)).unionByName(copies.withColumn("copy", F.lit(1)))
    return dealt.repartition(parts, "part").sortWithinPartitions("part", "copy", "key", "text")


def digest(docs: DataFrame) -> DataFrame:
    """Every document's and its edited text's fingerprints; see `edited`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple | None = None  # the last row of a stretch awaits the one after it
        for batch in batches:
            keys, texts, parts, copies = (batch.column(batch.schema.get_field_index(c)) for c in ("key", "text", "part", "copy"))
            lengths = texts.to_pylist()
            for lo, hi in slices(lengths):
                rows = list(zip(keys.slice(lo, hi - lo).to_pylist(), lengths[lo:hi], parts.slice(lo, hi - lo).to_pylist(), copies.slice(lo, hi - lo).to_pylist(), strict=True))
                rows = [held, *rows] if held else rows
                held = rows[-1]
                pairs = [(a[0], a[1], b[1]) for a, b in zip(rows, rows[1:], strict=False) if not a[3] and a[2] == b[2]]
                if pairs:
                    yield compared(pairs)

    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    return with_next(few_rows(docs)).mapInArrow(run, schema)


def edited(text: str, following: str) -> str:
    """The last half of the text (rounded down) replaced by the first as many characters of the following one."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def compared(pairs: list[tuple[int, str, str]]) -> pa.RecordBatch:
    changed = [edited(t, n) for _, t, n in pairs]
    own, new, after = vectors([t for _, t, _ in pairs]), vectors(changed), vectors([n for _, _, n in pairs])
    return pa.RecordBatch.from_pydict(
        {
            "doc_id": pa.array([None if k == NO_ID else k for k, _, _ in pairs], pa.int64()),
            "n_chars": pa.array([len(t) for _, t, _ in pairs], pa.int64()),
            "edited_sha256": pa.array([hashlib.sha256(t.encode()).hexdigest() for t in changed], pa.string()),
            "fingerprint": pa.array([v.tobytes().hex() for v in own], pa.string()),
            "edited_fingerprint": pa.array([v.tobytes().hex() for v in new], pa.string()),
            "near_edited": pa.array(likeness(own, new)),
            "near_next": pa.array(likeness(own, after)),
        }
    )


def op5_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(read_table(spark, sf_dir, "documents"))
