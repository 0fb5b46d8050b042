"""Removal of word passages repeated from earlier documents, by difference-cover anchors.

Windows of `WINDOW` words are matched.  Hashes of `ANCHOR` words are taken only at the positions of a document that
are in a difference cover modulo `PERIOD`: for any two positions there is a shift below the period that moves both
into the cover, so equal windows share an anchor at the same place in both as long as PERIOD + ANCHOR - 1 <= WINDOW.

1. Which anchors occur in two documents?  Asked by block (see core.answers), so a passage in a third of all documents
   costs one entry a block.
2. Around those, anchors extend to candidate windows, and their hashes ask for the smallest doc_id that holds them.
   A window is identified by 128 bits: two hashes of the two independent 64-bit hashes of each of its words.
3. Words covered by a window that also starts in a document with a smaller id go.

Null and empty texts have no words; texts of any length are read whole. Rows with equal doc_ids are one document here:
neither is smaller, so exact repeats of a row remove nothing from each other. A null doc_id is the smallest. Only the
columns doc_id and text are read, and no others are returned, so none can clash. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from erasureml.llm.core import Block, Words, answer_of, answers, attach, complete, distinct, each_block, ngram_hash, read_table, run_of, spread, text_blocks

WINDOW, ANCHOR, PERIOD = 13, 7, 7
# Residues modulo 7 whose differences are all residues.
COVER = (0, 1, 3)


class Scan:
    """The word hashes of a block, and for every word its row and its place in the document."""

    def __init__(self, block: Block) -> None:
        hashes, checks, counts = [np.zeros(0, np.uint64)], [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for i, j in block.chunks():
            words = Words(block, i, j)
            hashes.append(words.hash), checks.append(words.check), counts.append(words.counts)
        self.hash, self.check, self.counts = np.concatenate(hashes), np.concatenate(checks), np.concatenate(counts)
        self.ends = np.cumsum(self.counts)
        self.row = np.repeat(np.arange(len(self.counts)), self.counts)
        self.place = np.arange(len(self.hash)) - np.repeat(self.ends - self.counts, self.counts)
        self.ids = block.doc_ids[self.row]

    def anchors(self) -> tuple[np.ndarray, np.ndarray]:
        """Positions of all anchors and their hashes."""
        ok = complete(self.ends, ANCHOR, len(self.hash))
        ok &= np.isin(np.arange(PERIOD), COVER)[self.place[: len(ok)] % PERIOD]
        at = np.flatnonzero(ok)
        return at, ngram_hash(self.hash, ANCHOR)[at]

    def windows(self, block: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Positions of the windows that hold a repeated anchor, and both of their hashes."""
        at, h = self.anchors()
        _, order, runs = distinct(h)
        hit = at[answer_of(block.row, "repeated")[run_of(order, runs)] > 0] if len(h) else at
        total = np.zeros(len(self.hash) + 1, np.int64)
        total[hit + 1] = 1
        total = np.cumsum(total)
        ok = complete(self.ends, WINDOW, len(self.hash))
        n = len(ok)
        ok &= total[WINDOW - ANCHOR + 1 :][:n] - total[:n] > 0
        at = np.flatnonzero(ok)
        return at, ngram_hash(self.hash, WINDOW, at=at), ngram_hash(self.check, WINDOW, 1, at)


def ask_anchors(block: Block) -> tuple[np.ndarray, list[np.ndarray]]:
    scan = Scan(block)
    at, h = scan.anchors()
    keys, order, runs = distinct(h)
    ids = scan.ids[at][order]
    return keys, [np.minimum.reduceat(ids, runs), np.maximum.reduceat(ids, runs)] if len(ids) else [ids, ids]


def repeated(values: list[np.ndarray], at: np.ndarray) -> list[np.ndarray]:
    low, high = values
    return [spread(np.minimum.reduceat(low, at) < np.maximum.reduceat(high, at), at, len(low))]


def ask_windows(block: Block) -> tuple[np.ndarray, list[np.ndarray]]:
    scan = Scan(block)
    at, h, check = scan.windows(block)
    keys, order, runs = distinct(h, check)
    ids = scan.ids[at][order]
    return keys, [check[order[runs]], np.minimum.reduceat(ids, runs) if len(ids) else ids]


def earlier(values: list[np.ndarray], at: np.ndarray) -> list[np.ndarray]:
    """Whether a smaller id holds the window than any that the block has."""
    low = values[0]
    return [spread(np.minimum.reduceat(low, at), at, len(low)) < low]


def removed_words(block: Block) -> tuple[Scan, np.ndarray]:
    """Which words of the block go."""
    scan = Scan(block)
    at, h, check = scan.windows(block)
    _, order, runs = distinct(h, check)
    cover = np.zeros(len(scan.hash) + 1, np.int64)
    if len(h):
        ids = scan.ids[at]
        k = run_of(order, runs)
        gone = at[(answer_of(block.row, "earlier")[k] > 0) | (ids > np.minimum.reduceat(ids[order], runs)[k])]
        cover[gone] += 1
        cover[gone + WINDOW] -= 1
    return scan, np.cumsum(cover)[: len(scan.hash)] > 0


def matched(docs: DataFrame) -> DataFrame:
    """Blocks of docs with what `removed_words` needs."""
    blocks = text_blocks(docs)
    marked = attach(blocks, answers(blocks, ask_anchors, repeated), "repeated")
    return attach(marked, answers(marked, ask_windows, earlier, wide=True), "earlier")


def deduplicated(docs: DataFrame) -> DataFrame:
    """(doc_id, text of the words that stay, joined by a space)."""
    return each_block(matched(docs), lambda b: _texts(b, lambda kept: kept.decode(), "text"), "doc_id long, n_words long, n_removed long, text string")


def _texts(block: Block, last, name: str = "kept_sha256") -> Iterator[pd.DataFrame]:
    scan, gone = removed_words(block)
    n_gone = np.diff(np.concatenate([[0], np.cumsum(gone)])[np.concatenate([[0], scan.ends])]) if len(scan.ends) else scan.ends
    out = []
    for i, (end, n) in enumerate(zip(scan.ends.tolist(), scan.counts.tolist(), strict=True)):
        words = block.text(i).split()
        if n_gone[i]:
            stay = ~gone[end - n : end]
            words = [w for w, s in zip(words, stay.tolist(), strict=True) if s]
        out.append(last(b" ".join(words)))
    yield pd.DataFrame({"doc_id": block.ids_out(), "n_words": scan.counts, "n_removed": n_gone, name: out})


def op9_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    blocks = matched(read_table(spark, sf_dir, "documents"))
    return each_block(blocks, lambda b: _texts(b, lambda kept: hashlib.sha256(kept).hexdigest()), "doc_id long, n_words long, n_removed long, kept_sha256 string")


ORACLE = r"""
WITH w AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
     v AS (SELECT doc_id, i, array_to_string(ws[i:i + 12], ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 11)) AS i FROM w)),
     f AS (SELECT k, min(doc_id) AS first FROM v GROUP BY k),
     c AS (SELECT DISTINCT v.doc_id, v.i + o.range AS i FROM v JOIN f ON v.k = f.k AND f.first < v.doc_id CROSS JOIN range(13) o),
     p AS (SELECT doc_id, unnest(range(1, len(ws) + 1)) AS i, unnest(ws) AS word FROM w),
     s AS (SELECT p.doc_id, string_agg(p.word, ' ' ORDER BY p.i) AS kept, count(*) AS n FROM p LEFT JOIN c ON p.doc_id = c.doc_id AND p.i = c.i WHERE c.i IS NULL GROUP BY p.doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(len(ws) - coalesce(s.n, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM w LEFT JOIN s ON w.doc_id = s.doc_id
"""
