"""Benchmark decontamination by size-partitioned MinHash containment search.

A document contains a test item if it holds at least `threshold` of the item's distinct shingles (five words; an item
of fewer words is one shingle of all of them).  Words are runs of letters and digits in lower case.

Containment of a short item in a long document can't be read off their Jaccard similarity, so the sketch is one-sided:
an item is sketched by its m smallest shingle hashes and a document by all of its own.  An item of n shingles may
miss n - ceil(threshold n) of them, so with one more than that in the sketch every document that contains it shares
a sketch hash: m depends on the item's size, which is why items are partitioned by size, and documents with fewer
shingles than the smallest item of a partition needs skip it.  Candidates are verified with the shingles themselves.

The index of the items is sent to the tasks if their text has at most `index_bytes`.  Beyond that, the documents are
kept with a number for every row; the hashes of theirs that pass a bit map of the sketches (of a fixed size) meet the
sketches in a join, and each row then gets its candidates' texts and verifies them in the same way, by the shingles.  Both
ways give the same rows: a document is a row, whatever its doc_id, so null and repeated ids are told apart.

Null and empty texts hold no item; items without a word are contained in nothing, and items of the same id are items of
their own.  Documents of any length are read whole.  `pairs` returns no column of the caller's but doc_id and item_id;
`stage` returns all columns of the documents as they came.  Empty tables, of documents or of items, give no pairs.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.llm.core import Texts, Words, complete, few_rows, mix, ngram_hash, read_table, reliable

SIZE, THRESHOLD = 5, 0.8
INDEX_BYTES = 32 << 20
_WORD = re.compile("[a-z0-9\x80-\U0010ffff]+")
#: ASCII other than letters and digits parts words.
PARTS = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])


def shingles(text: str | None, size: int) -> set[tuple[str, ...]]:
    w = _WORD.findall((text or "").lower())
    return {tuple(w[i : i + size]) for i in range(len(w) - size + 1)}


def lowered(column: pa.Array) -> pa.Array:
    return pc.utf8_lower(pc.fill_null(column, ""))


class Index:
    """Sketches of all items, by shingle length, and the shingles to verify with."""

    def __init__(self, items: list[tuple], threshold: float = THRESHOLD, size: int = SIZE) -> None:
        self.threshold = threshold
        self.items: list[tuple] = []
        held: dict[int, list[tuple[int, int]]] = {}
        for item_id, text in items:
            n = len(_WORD.findall((text or "").lower()))
            if not n:
                continue
            length = min(n, size)
            own = shingles(text, length)
            at = len(self.items)
            self.items.append((item_id, length, own, need(len(own), threshold)))
            hashes = np.unique(hashed(lowered(pa.array([text])), length)[0])
            held.setdefault(length, []).extend((int(h), at) for h in hashes[: sketch_size(len(hashes), threshold)])
        #: by shingle length: (partition of sizes) -> hashes, items and the fewest shingles needed
        self.tables: dict[int, list[tuple[np.ndarray, np.ndarray, int]]] = {}
        for length, rows in held.items():
            classes: dict[int, list[tuple[int, int]]] = {}
            for h, at in rows:
                classes.setdefault(len(self.items[at][2]).bit_length(), []).append((h, at))
            self.tables[length] = []
            for rows_ in classes.values():
                rows_.sort()
                self.tables[length].append((np.array([h for h, _ in rows_], np.uint64), np.array([a for _, a in rows_]), min(self.items[a][3] for _, a in rows_)))

    def candidates(self, column: pa.Array) -> list[set[int]]:
        """For every text, the items that share a sketch hash with it."""
        found: list[set[int]] = [set() for _ in range(len(column))]
        for length, tables in self.tables.items():
            h, doc = hashed(column, length)
            sizes = np.bincount(doc, minlength=len(column))
            for keys, at, least in tables:
                bits = np.zeros(1 << 16, bool)
                bits[keys >> np.uint64(48)] = True
                hit = np.flatnonzero(bits[h >> np.uint64(48)])
                hit = hit[sizes[doc[hit]] >= least]
                lo, hi = np.searchsorted(keys, h[hit], "left"), np.searchsorted(keys, h[hit], "right")
                for k in np.flatnonzero(hi > lo).tolist():
                    found[doc[hit[k]]].update(at[lo[k] : hi[k]].tolist())
        return found

    def contained(self, column: pa.Array) -> Iterator[tuple[int, tuple, int, int]]:
        """(row, item_id, the item's shingles, those found) of all verified pairs."""
        for row, items in enumerate(self.candidates(lowered(column))):
            if items:
                text = column[row].as_py()
                own = {n: shingles(text, n) for n in {self.items[i][1] for i in items}}
                for i in sorted(items):
                    item_id, length, wanted, least = self.items[i]
                    shared = len(wanted & own[length])
                    if shared >= least:
                        yield row, item_id, len(wanted), shared


def need(n: int, threshold: float) -> int:
    return max(1, math.ceil(threshold * n - 1e-9))


def sketch_size(n: int, threshold: float) -> int:
    return n - need(n, threshold) + 1


def hashed(column: pa.Array, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all shingles of lower-cased texts, and the row of each."""
    texts = Texts.of(column)
    hashes, rows = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
    for i, j in texts.chunks():
        words = Words(texts, i, j, separators=PARTS)
        ok = complete(words.ends, length, len(words.hash))
        hashes.append(ngram_hash(words.hash, length)[ok])
        rows.append(np.repeat(np.arange(i, j), words.counts)[: len(ok)][ok])
    return np.concatenate(hashes), np.concatenate(rows)


def pairs(docs: DataFrame, items: DataFrame, threshold: float = THRESHOLD, size: int = SIZE, index_bytes: int = INDEX_BYTES) -> DataFrame:
    """(doc_id, item_id, n_item, n_shared, containment) of all pairs at or over the threshold."""
    index = small_index(items, threshold, size, index_bytes)
    if index is None:
        return joined(docs, items, threshold, size)
    kind = dict(items.dtypes)["item_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_pylist()
            got = [(ids[r], item, n, s, s / n) for r, item, n, s in index.contained(batch.column(1))]
            if got:
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*got, strict=True)], ["doc_id", "item_id", "n_item", "n_shared", "containment"])

    return few_rows(docs).select(F.col("doc_id").cast("long"), "text").mapInArrow(run, f"doc_id long, item_id {kind}, n_item long, n_shared long, containment double")


def small_index(items: DataFrame, threshold: float = THRESHOLD, size: int = SIZE, index_bytes: int = INDEX_BYTES) -> Index | None:
    """The index, if the items' text is small enough to be sent around."""
    total = items.agg(F.sum(F.octet_length("text")).alias("n")).first()["n"] or 0
    if total > index_bytes:
        return None
    return Index([(r["item_id"], r["text"]) for r in items.select("item_id", "text").orderBy("item_id").collect()], threshold, size)


ROW = "_containment_row"
MAP_BITS = 25


def rows_numbered(docs: DataFrame) -> DataFrame:
    """docs, kept, with a number for every row."""
    return reliable(docs.withColumn(ROW, F.monotonically_increasing_id()))


def sketches(items: DataFrame, threshold: float, size: int) -> DataFrame:
    """(item_no, length, least, h): the sketch of every item."""
    fields = "item_no long, length int, least int, h long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got: list[tuple] = []
            for no, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                n = len(_WORD.findall((text or "").lower()))
                if n:
                    own = np.unique(hashed(lowered(pa.array([text])), min(n, size))[0])
                    got += [(no, min(n, size), need(len(own), threshold), int(h)) for h in own[: sketch_size(len(own), threshold)].view(np.int64)]
            columns = list(zip(*got, strict=True)) or [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int32(), pa.int32(), pa.int64()), strict=True)], ["item_no", "length", "least", "h"])

    return items.select("item_no", "text").mapInArrow(run, fields)


def bit_map(sketch: DataFrame) -> dict[int, np.ndarray]:
    """By shingle length, which bits the sketches' hashes set: 2^MAP_BITS bits, whatever their number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for batch in batches:
            length, h = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            for n in np.unique(length).tolist():
                at = np.unique(bit_of(h[length == n].view(np.uint64)))
                held[n] = np.union1d(held[n], at) if n in held else at
        for n, at in held.items():
            yield pa.RecordBatch.from_pydict({"length": pa.array(np.full(len(at), n, np.int32)), "bit": pa.array(at)})

    found = sketch.select("length", "h").mapInArrow(run, "length int, bit long").distinct()
    words = found.groupBy("length", F.floor(F.col("bit") / 64).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, int(bit % 64))")).alias("bits")).toPandas()
    out = {}
    for n, own in words.groupby("length"):  # at most size x 2^MAP_BITS / 64 rows
        out[int(n)] = np.zeros(1 << MAP_BITS - 6, np.uint64)
        out[int(n)][own["word"].to_numpy()] = own["bits"].to_numpy(np.int64).view(np.uint64)
    return out


def bit_of(h: np.ndarray) -> np.ndarray:
    return (mix(h) >> np.uint64(64 - MAP_BITS)).astype(np.int64)


def candidate_rows(docs: DataFrame, items: DataFrame, threshold: float, size: int) -> DataFrame:
    """(row, its text, texts: (item_id, text) of the items that share a sketch hash with it). docs: with ROW."""
    numbered = reliable(items.select("item_id", "text").withColumn("item_no", F.monotonically_increasing_id()))
    sketch = reliable(sketches(numbered, threshold, size))
    bits = bit_map(sketch)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text, keys = lowered(batch.column(1)), batch.column(0)
            for length, marks in bits.items():
                h, row = hashed(text, length)
                at = bit_of(h)
                hit = (marks[at >> 6] >> (at & 63).astype(np.uint64) & np.uint64(1)).astype(bool)
                h, row = h[hit], row[hit]
                order = np.lexsort((h, row))
                h, row = h[order], row[order]
                new = np.concatenate([[True], (h[1:] != h[:-1]) | (row[1:] != row[:-1])])[: len(h)]
                yield pa.RecordBatch.from_arrays([keys.take(pa.array(row[new])), pa.array(np.full(int(new.sum()), length, np.int32)), pa.array(h[new].view(np.int64))], [ROW, "length", "h"])

    have = few_rows(docs).select(ROW, "text").mapInArrow(run, f"{ROW} long, length int, h long")
    met = have.join(sketch, ["length", "h"]).select(ROW, "item_no").distinct()
    texts = met.join(numbered, "item_no").groupBy(ROW).agg(F.collect_list(F.struct("item_id", "text")).alias("_items"))
    return docs.join(texts, ROW)


def verified(batch: pa.RecordBatch, threshold: float, size: int) -> Iterator[tuple]:
    """(row of the batch, item_id, the item's shingles, those found) from text and _items."""
    for row, (text, items) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
        own: dict[int, set] = {}
        for item in items:
            length = min(len(_WORD.findall((item["text"] or "").lower())), size)
            wanted = shingles(item["text"], length)
            if length not in own:
                own[length] = shingles(text, length)
            shared = len(wanted & own[length])
            if shared >= need(len(wanted), threshold):
                yield row, item["item_id"], len(wanted), shared


def joined(docs: DataFrame, items: DataFrame, threshold: float = THRESHOLD, size: int = SIZE) -> DataFrame:
    """The same pairs without an index in memory."""
    kind = dict(items.dtypes)["item_id"]
    found = candidate_rows(rows_numbered(docs.select(F.col("doc_id").cast("long"), "text")), items, threshold, size)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(2).to_pylist()
            got = [(ids[r], item, n, s, s / n) for r, item, n, s in verified(batch, threshold, size)]
            if got:
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*got, strict=True)], ["doc_id", "item_id", "n_item", "n_shared", "containment"])

    return found.select("text", "_items", "doc_id").mapInArrow(run, f"doc_id long, item_id {kind}, n_item long, n_shared long, containment double")


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


ORACLE = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[a-z0-9\x{80}-\x{10FFFF}]+') AS ws FROM documents),
     b AS (SELECT item_id, regexp_extract_all(lower(coalesce(text, '')), '[a-z0-9\x{80}-\x{10FFFF}]+') AS ws FROM benchmark),
     n AS (SELECT item_id, ws, least(len(ws), 5) AS k FROM b WHERE len(ws) > 0),
     i AS (SELECT DISTINCT item_id, k, array_to_string(ws[p:p + k - 1], ' ') AS s
           FROM (SELECT item_id, ws, k, unnest(range(1, len(ws) - k + 2)) AS p FROM n)),
     l AS (SELECT DISTINCT k FROM n),
     d AS (SELECT DISTINCT doc_id, k, array_to_string(ws[p:p + k - 1], ' ') AS s
           FROM (SELECT doc_id, ws, k, unnest(range(1, greatest(len(ws) - k + 2, 1))) AS p FROM w, l)),
     t AS (SELECT item_id, count(*) AS n_item FROM i GROUP BY item_id),
     m AS (SELECT d.doc_id, i.item_id, count(*) AS n_shared FROM i JOIN d ON i.k = d.k AND i.s = d.s GROUP BY 1, 2)
SELECT m.doc_id, m.item_id, t.n_item, m.n_shared, m.n_shared / t.n_item AS containment
FROM m JOIN t ON m.item_id = t.item_id WHERE m.n_shared >= 0.8 * t.n_item - 1e-9
"""


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that contain no item."""
    return uncontaminated(docs, read_table(spark, sf_dir, "benchmark"))


def uncontaminated(docs: DataFrame, items: DataFrame, index_bytes: int = INDEX_BYTES) -> DataFrame:
    index = small_index(items, index_bytes=index_bytes)
    if index is None:
        columns = docs.columns
        numbered = rows_numbered(docs.toDF(*(f"c{i}" for i in range(len(columns)))).withColumn("text", F.col(f"c{columns.index('text')}")))
        found = candidate_rows(numbered, items, THRESHOLD, SIZE)

        def dirty(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = sorted({r for r, *_ in verified(batch, THRESHOLD, SIZE)})
                yield pa.RecordBatch.from_arrays([batch.column(2).take(pa.array(rows, pa.int64()))], [ROW])

        gone = found.select("text", "_items", ROW).mapInArrow(dirty, f"{ROW} long")
        return numbered.join(gone, ROW, "left_anti").select(*(F.col(f"c{i}").alias(c) for i, c in enumerate(columns)))
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            clean = np.ones(batch.num_rows, bool)
            clean[[row for row, *_ in index.contained(batch.column(at))]] = False
            yield batch.filter(pa.array(clean))

    return few_rows(docs).mapInArrow(run, docs.schema)
