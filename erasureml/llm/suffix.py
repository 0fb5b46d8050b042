"""Exact removal of repeated byte strings by two-stage suffix sorting.

A window is `LENGTH` bytes of one document's UTF-8 text.  A byte goes if a window over it also starts anywhere else.

1. Anchors.  Every window has an anchor: the leftmost smallest hash of `GRAM` bytes in it.  Equal windows have equal
   anchors at the same place, so a window whose anchor hash occurs once in the corpus needs no look (asked by block,
   see core.answers).
2. Suffix sorting.  The windows of repeated anchors, with the bytes they span, are dealt by anchor hash.  There the
   suffixes smaller than their successor are sorted directly; the others are induced from their successors by one
   scan over the buckets of first bytes, whole arrays at a time.  Neighbours with a common prefix of LENGTH are repeats.
3. Anchors with over `HOT` occurrences would gather in one task.  Their windows are dealt by their own 128-bit hash
   (core.range_hash: two independent 64-bit hashes) instead: a window that a block holds twice is a repeat at once, and
   a block asks for each of its windows once, so a group of copies of any size is spread over all tasks.  Which of the two
   ways a window goes doesn't change what is a repeat: of 10^14 windows two different ones share 128 bits with a
   probability of 10^-11.

Null and empty texts have no bytes and lose none; texts of any length are read whole. Rows with equal or null doc_ids are
documents of their own, so every byte of a repeated row of 200 bytes or more goes, from all of its copies. Only
doc_id and text are read and no other column is returned. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.llm.core import LANE_BYTES, Block, Roller, _cuts, answer_of, answers, attach, distinct, each_block, expand, mix, pack, range_hash, read_table, reliable, run_of, shuffle_parts, spread, squeeze, text_blocks, unpack

LENGTH, GRAM = 200, 64
WIDTH = LENGTH - GRAM + 1
HOT = 256
SEGMENT = 1 << 18
FINER = 4  # hash ranges a shuffle partition: a range is sorted in memory, and small ones even out
SORT_AT_ONCE = 1 << 19
ROLL = Roller(50077)
_PLACE = np.uint64((1 << 22) - 1)


# ---------------------------------------------------------------- two-stage suffix sorting


def suffix_order(text: bytes, wanted: np.ndarray, depth: int) -> np.ndarray:
    """The wanted positions (a mask) in an order of suffixes that is lexicographic to at least `depth` bytes."""
    t = np.frombuffer(text, np.uint8)
    n = len(t)
    change = np.flatnonzero(t[1:] != t[:-1])  # i: t[i] and t[i + 1] differ
    runs = np.diff(np.concatenate([[-1], change]))
    smaller = np.concatenate([np.repeat(t[change] < t[change + 1], runs), np.zeros(n - (change[-1] + 1 if len(change) else 0), bool)])
    # an induced suffix needs its successor: take positions up to the next one that is sorted directly
    last = np.flatnonzero(wanted & ~np.append(wanted[1:], False))
    direct = np.flatnonzero(smaller)
    until = np.append(direct, n - 1)[np.searchsorted(direct, last)]
    grow = np.zeros(n + 1, np.int64)
    np.add.at(grow, last, 1)
    np.add.at(grow, until + 1, -1)
    used = wanted | (np.cumsum(grow)[:n] > 0)
    induced = used & ~smaller
    direct = np.flatnonzero(used & smaller)
    keys = [text[p : p + depth] for p in direct.tolist()]
    direct = direct[np.array(sorted(range(len(keys)), key=keys.__getitem__), np.int64)]
    heads = np.searchsorted(t[direct], np.arange(257))
    waiting: list[list[np.ndarray]] = [[] for _ in range(256)]
    if n and induced[n - 1]:
        waiting[t[n - 1]].append(np.array([n - 1]))
    out = []
    for c in range(256):
        own = list(waiting[c])
        new = np.concatenate(own) if own else np.zeros(0, np.int64)
        while len(new):  # runs of c, one longer each time
            before = new[new > 0] - 1
            new = before[induced[before] & (t[before] == c)]
            own.append(new)
        bucket = np.concatenate([*own, direct[heads[c] : heads[c + 1]]]).astype(np.int64)
        if not len(bucket):
            continue
        out.append(bucket)
        before = bucket[bucket > 0] - 1
        before = before[induced[before] & (t[before] > c)]
        if len(before):
            order = np.argsort(t[before], kind="stable")
            before = before[order]
            at = np.flatnonzero(np.diff(t[before])) + 1
            for part in np.split(before, at):
                waiting[t[part[0]]].append(part)
    order = np.concatenate([np.zeros(0, np.int64), *out])
    return order[wanted[order]]


def repeated_starts(text: bytes, wanted: np.ndarray, length: int) -> np.ndarray:
    """Mask of the wanted positions whose next `length` bytes (all in the text) equal those at another one."""
    order = suffix_order(text, wanted, length)
    padded = text + bytes(8)
    words = np.ndarray(len(padded) - 7, "<u8", padded, strides=(1,))
    a, b = order[:-1], order[1:]
    pair = np.arange(len(a))
    for k in [*range(0, length - 7, 8), *([length - 8] if length % 8 else [])]:
        same = words[a[pair] + k] == words[b[pair] + k]
        pair = pair[same]
    out = np.zeros(len(text), bool)
    out[a[pair]] = out[b[pair]] = True
    return out


# ---------------------------------------------------------------- anchors


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    n = len(x) - width + 1
    full = np.full(-(-len(x) // width) * width, np.iinfo(np.uint64).max, np.uint64)
    full[: len(x)] = x
    rows = full.reshape(-1, width)
    left = np.minimum.accumulate(rows, axis=1).ravel()
    right = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(right[:n], left[width - 1 : width - 1 + n])


def anchors(block: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of windows with the same anchor: the first window's place in the block, their number, the anchor's hash."""
    data = np.frombuffer(block.body, np.uint8)
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    ends = np.cumsum(block.lens)
    for i, j in block.chunks(SEGMENT):
        stop = int(ends[j - 1])
        for lo in range(int(block.starts[i]), stop, SEGMENT):
            part = data[lo : min(stop, lo + SEGMENT + LENGTH - 1)] if j == i + 1 else data[lo:stop]
            if len(part) >= LENGTH:
                rows = np.clip(ends[i:j] - lo, 0, len(part))
                found.append(_runs(part, rows, lo))
            if j > i + 1:
                break
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def _runs(part: np.ndarray, ends: np.ndarray, lo: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    prefix = ROLL.prefix(part)
    at = np.arange(len(part) - GRAM + 1)
    h = ROLL.ranges(prefix, at, at + GRAM)
    low = _sliding_min(h & ~_PLACE | at.astype(np.uint64), WIDTH)
    n = len(low)
    place = (low & _PLACE).astype(np.int64)
    valid = np.arange(n) + LENGTH <= np.repeat(ends, np.diff(ends, prepend=0))[:n]
    new = np.concatenate([[True], (place[1:] != place[:-1]) | ~valid[:-1]])
    first = np.flatnonzero(valid & new)
    stop = np.flatnonzero(valid & np.append(new[1:] | ~valid[1:], True))
    # smallest hashes are small: mixed again they spread over all ranges
    return first + lo, stop - first + 1, mix(h[place[first]])


def ask_anchors(block: Block) -> tuple[np.ndarray, list[np.ndarray]]:
    h = anchors(block)[2]
    keys, _, at = distinct(h)
    return keys, [np.diff(np.append(at, len(h)))]


def occurrences(values: list[np.ndarray], at: np.ndarray) -> list[np.ndarray]:
    return [spread(np.add.reduceat(values[0], at), at, len(values[0]))]


# ---------------------------------------------------------------- candidates

SORT, COUNT, DONE = 0, 1, 2
ROWS = "kind int, part int, block_id long, load binary, body binary"


def ranges_of(places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted places as runs (first, number)."""
    cut = np.flatnonzero(np.diff(places) != 1) + 1
    first = places[np.concatenate([[0], cut])] if len(places) else places
    return first, np.diff(np.concatenate([[0], cut, [len(places)]])) if len(places) else places


def candidates(parts: int, hot: int):
    """work for each_block: windows to sort, to count, and repeats that the block shows by itself."""

    def work(block: Block) -> Iterator[pd.DataFrame]:
        first, count, h = anchors(block)
        _, order, at = distinct(h)
        total = answer_of(block.row, "anchors")[run_of(order, at)] if len(h) else np.zeros(0, np.int64)
        rows = []
        sort = np.flatnonzero((total > 1) & (total <= hot))
        sort = sort[np.argsort(h[sort])]
        cuts = _cuts(h[sort], parts)
        for p in range(parts):
            own = sort[cuts[p] : cuts[p + 1]]
            if len(own):
                texts = b"".join([block.body[s : s + n + LENGTH - 1] for s, n in zip(first[own].tolist(), count[own].tolist(), strict=True)])
                rows.append((SORT, p, block.block_id, pack(h[own], first[own], count[own]), squeeze(texts)))
        many = np.flatnonzero(total > hot)
        if len(many):
            n = count[many]
            ends = np.cumsum(n)
            place = np.repeat(first[many] - (ends - n), n) + np.arange(int(ends[-1]))
            window, check = _window_hashes(block, place)
            keys, order, at = distinct(window, check)
            size = np.diff(np.append(at, len(order)))
            here = np.sort(place[order[np.repeat(size > 1, size)]])
            if len(here):
                rows.append((DONE, 0, block.block_id, pack(*ranges_of(here)), b""))
            cuts = _cuts(keys, parts)
            for p in range(parts):
                if cuts[p + 1] > cuts[p]:
                    one = order[at[cuts[p] : cuts[p + 1]]]
                    rows.append((COUNT, p, block.block_id, pack(keys[cuts[p] : cuts[p + 1]], place[one], check[one]), b""))
        yield pd.DataFrame(rows, columns=["kind", "part", "block_id", "load", "body"])

    return work


def _window_hashes(block: Block, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both hashes of the windows at sorted places: the last of the states over eight bytes at a time."""
    data = np.frombuffer(block.body, np.uint8)
    out, i = [(np.zeros(0, np.uint64),) * 2], 0
    while i < len(place):
        lo = int(place[i])
        j = int(np.searchsorted(place, lo + SEGMENT))
        part = data[lo : lo + SEGMENT + LENGTH]
        own = place[i:j] - lo
        states = [range_hash(part, own + k, own + min(k + LANE_BYTES, LENGTH)) for k in range(0, LENGTH, LANE_BYTES)]
        out.append(tuple(chained([s[lane] for s in states]) for lane in (0, 1)))
        i = j
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def chained(hashes: list[np.ndarray]) -> np.ndarray:
    total = hashes[0]
    for h in hashes[1:]:
        total = mix(total) ^ h
    return mix(total)


def _runs_by_block(blocks: np.ndarray, first: np.ndarray, count: np.ndarray) -> pd.DataFrame:
    order = np.lexsort((first, blocks))
    blocks, first, count = blocks[order], first[order], count[order]
    if not len(blocks):
        return pd.DataFrame({"block_id": blocks, "load": []})
    at = np.flatnonzero(np.concatenate([[True], blocks[1:] != blocks[:-1]]))
    stop = np.append(at[1:], len(blocks))
    return pd.DataFrame({"block_id": blocks[at], "load": [pack(first[i:j], count[i:j]) for i, j in zip(at, stop, strict=True)]})


def sort_part(frame: pd.DataFrame) -> pd.DataFrame:
    """Repeats among the windows of a range of anchor hashes."""
    meta = [unpack(x) for x in frame["load"]]
    texts = [expand(x) for x in frame["body"]]
    source = np.repeat(np.arange(len(meta)), [len(m[0]) for m in meta])
    h, first, count = (np.concatenate([m[k] for m in meta]) for k in range(3))
    size = count + LENGTH - 1
    offset = np.concatenate([np.cumsum(m[2] + LENGTH - 1) - (m[2] + LENGTH - 1) for m in meta])
    order = np.argsort(h.view(np.uint64))
    blocks = frame["block_id"].to_numpy()
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    i = 0
    group_end = np.append(np.flatnonzero(np.diff(h[order])) + 1, len(order))
    total = np.cumsum(size[order])
    while i < len(order):
        want = (total[i - 1] if i else 0) + SORT_AT_ONCE
        k = int(np.searchsorted(group_end, max(i + 1, int(np.searchsorted(total, want)))))
        j = int(group_end[min(k, len(group_end) - 1)])
        own = order[i:j]
        text = b"".join([texts[source[r]][offset[r] : offset[r] + size[r]] for r in own.tolist()])
        at = np.cumsum(size[own]) - size[own]
        wanted = np.zeros(len(text) + 1, np.int64)
        np.add.at(wanted, at, 1)
        np.add.at(wanted, at + count[own], -1)
        hit = np.flatnonzero(repeated_starts(text, np.cumsum(wanted)[:-1] > 0, LENGTH))
        if len(hit):
            row = np.searchsorted(at, hit, "right") - 1
            place = hit - at[row] + first[own[row]]
            new = np.concatenate([[True], (row[1:] != row[:-1]) | (np.diff(hit) != 1)])
            start = np.flatnonzero(new)
            found.append((blocks[source[own[row[start]]]], place[start], np.diff(np.append(start, len(hit)))))
        i = j
    if not found:
        return pd.DataFrame({"block_id": np.zeros(0, np.int64), "load": []})
    return _runs_by_block(*(np.concatenate(x) for x in zip(*found, strict=True)))


def count_part(frame: pd.DataFrame) -> pd.DataFrame:
    """Windows of a range of hashes that more than one block holds."""
    meta = [unpack(x) for x in frame["load"]]
    h, place, check = (np.concatenate([m[k] for m in meta]) for k in range(3))
    blocks = np.repeat(frame["block_id"].to_numpy(), [len(m[0]) for m in meta])
    _, order, at = distinct(h.view(np.uint64), check)
    size = np.diff(np.append(at, len(order)))
    hit = order[np.repeat(size > 1, size)]
    return _runs_by_block(blocks[hit], place[hit], np.ones(len(hit), np.int64))


def matched(docs: DataFrame, hot: int = HOT) -> DataFrame:
    """Blocks of docs with the runs of repeated windows."""
    blocks = text_blocks(docs)
    marked = attach(blocks, answers(blocks, ask_anchors, occurrences), "anchors")
    found = reliable(each_block(marked, candidates(FINER * shuffle_parts(docs.sparkSession), hot), ROWS))
    kind = "block_id long, load binary"
    runs = (
        found.where(F.col("kind") == SORT).groupBy("part").applyInPandas(sort_part, kind)
        .union(found.where(F.col("kind") == COUNT).select("part", "block_id", "load").groupBy("part").applyInPandas(count_part, kind))
        .union(found.where(F.col("kind") == DONE).select("block_id", "load"))
    )
    return attach(blocks, reliable(runs.groupBy("block_id").agg(F.collect_list("load").alias("answers")), dealt=True), "runs")


def removed_bytes(block: Block) -> np.ndarray:
    cover = np.zeros(len(block.body) + 1, np.int32)
    for load in block.row.runs if block.row.runs is not None else ():
        first, count = unpack(load)
        np.add.at(cover, first, 1)
        np.add.at(cover, first + count + LENGTH - 1, -1)
    return np.cumsum(cover)[:-1] > 0


def _rows(block: Block, last, name: str) -> Iterator[pd.DataFrame]:
    gone = removed_bytes(block)
    removed = np.diff(np.concatenate([[0], np.cumsum(gone)])[block.starts])
    opens = gone & ~np.concatenate([[False], gone[:-1]])
    inner = block.starts[:-1][block.lens > 0]
    opens[inner] = gone[inner]
    spans = np.diff(np.concatenate([[0], np.cumsum(opens)])[block.starts])
    data, out = np.frombuffer(block.body, np.uint8), []
    for i, n in enumerate(removed.tolist()):
        lo, hi = block.starts[i], block.starts[i + 1]
        out.append(last(data[lo:hi][~gone[lo:hi]].tobytes() if n else block.body[lo:hi]))
    yield pd.DataFrame({"doc_id": block.ids_out(), "n_bytes": block.lens, "n_removed": removed, "n_spans": spans, name: out})


def deduplicated(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, text that stays; a character cut in two becomes U+FFFD)."""
    return each_block(matched(docs), lambda b: _rows(b, lambda kept: kept.decode("utf-8", "replace"), "text"), "doc_id long, n_bytes long, n_removed long, n_spans long, text string")


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    blocks = matched(read_table(spark, sf_dir, "documents"))
    return each_block(blocks, lambda b: _rows(b, lambda kept: hashlib.sha256(kept).hexdigest(), "kept_sha256"), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
