"""Encoding of texts by their distinct pieces.

A tokenizer first parts a text into pieces that it encodes independently.  For texts of ASCII and the letters of Latin-1
the parting is found on the bytes of many texts at once, and the library encodes every distinct piece only once.
Other texts, those with an apostrophe (which has rules of its own) and those with a string that the library matches
before all else (`special`) go through the library whole.

Pieces are equal only if all their bytes are: those of up to 16 bytes are two words and a length, which hold every byte;
a longer one is numbered by a dictionary of byte strings.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from erasureml.llm.core import _LOW, Texts, lanes_of, mix, run_of

MEMO = 1_000_000
LONG_BYTES = 64 << 20
BLANK, LETTER, DIGIT, MARK = range(4)
CLASS = np.array([BLANK if b in (9, 10, 11, 12, 13, 32) else DIGIT if 48 <= b < 58 else LETTER if b >= 128 or chr(b).isalpha() else MARK for b in range(256)], np.uint8)


def gather(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The indices of all ranges [first, first + n), one after the other."""
    ends = np.cumsum(n)
    return np.repeat(first - (ends - n), n) + np.arange(int(ends[-1]) if len(ends) else 0)


def exact_runs(h: np.ndarray, columns: tuple[np.ndarray, ...]) -> tuple[np.ndarray, np.ndarray]:
    """An order that puts equal rows of columns side by side, and where each run of them starts. h: a hash of the columns."""
    order = np.argsort(h)

    def edges(*by: np.ndarray) -> np.ndarray:
        out = np.zeros(len(order), bool)
        out[:1] = True
        for c in by:
            out[1:] |= c[order[1:]] != c[order[:-1]]
        return out

    new = edges(*columns)
    if (new & ~edges(h)).any():  # a hash that two different pieces share
        order = np.lexsort((*columns, h))
        new = edges(*columns)
    return order, np.flatnonzero(new)


class DistinctCoder:
    """`full` is the whole tokenizer; subclasses part texts (`part`) and encode new pieces (`made`)."""

    special: tuple[bytes, ...] = ()

    def __init__(self, full) -> None:
        self.full = full
        self.keys, self.codes = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self.held = tuple(np.zeros(0, np.uint64) for _ in range(3))  # the bytes and lengths behind keys
        self.long: dict[bytes, int] = {}
        self.long_bytes = 0
        self.flat, self.lens = np.zeros(0, np.uint32), np.zeros(0, np.int64)

    def part(self, texts: Texts, data: np.ndarray, lead: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The bytes to read pieces from, and where each piece begins and ends. lead: bytes after 0xC3."""
        raise NotImplementedError

    def made(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of pieces, and the number of each one's; of bytes that aren't a text, anything."""
        raise NotImplementedError

    def whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.full.encode_batch_fast(texts, add_special_tokens=False)]

    def singly(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        got = [e.ids for e in self.full.encode_batch_fast([p.decode("utf-8", "replace") for p in pieces], add_special_tokens=False)]
        lens = np.fromiter(map(len, got), np.int64, len(got))
        return np.fromiter((i for x in got for i in x), np.uint32, int(lens.sum())), lens

    def named(self, data: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, bool]:
        """Three numbers for every piece, equal only for equal bytes, and whether all of them may be kept."""
        n, lanes = hi - lo, lanes_of(data)
        a, b = lanes[lo] & _LOW[np.minimum(n, 8)], np.zeros(len(lo), np.uint64)
        more = np.flatnonzero(n > 8)
        b[more] = lanes[lo[more] + 8] & _LOW[np.minimum(n[more] - 8, 8)]
        size, keep = n.astype(np.uint64), True
        over = np.flatnonzero(n > 16)
        if len(over):
            body, number = data.tobytes(), []
            if self.long_bytes > LONG_BYTES:  # numbers of this call only
                known, keep = {}, False
            else:
                known = self.long
            for i, j in zip(lo[over].tolist(), hi[over].tolist(), strict=True):
                piece = body[i:j]
                k = known.get(piece)
                if k is None:
                    k = known[piece] = len(known)
                    self.long_bytes += (j - i) * keep
                number.append(k)
            a[over], b[over], size[over] = np.array(number, np.uint64), 0, 17 if keep else 18
        return a, b, size, keep

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and their number by text."""
        texts = Texts.of(column)
        data = np.frombuffer(texts.body, np.uint8)
        lead = np.concatenate([[False], data[:-1] == 0xC3]) if len(data) else np.zeros(0, bool)
        odd = (data >= 0x80) & ~lead & (data != 0xC3) | lead & ((data == 0x97) | (data == 0xB7)) | (data == 0x27) | (data >= 0x1C) & (data < 0x20)
        for word in self.special:
            at = texts.body.find(word)
            while at >= 0:
                odd[at] = True
                at = texts.body.find(word, at + 1)
        slow = np.diff(np.concatenate([[0], np.cumsum(odd)])[texts.starts]) > 0
        data, lo, hi = self.part(texts, data, lead)
        row = np.searchsorted(texts.starts, lo, "right") - 1
        use = ~slow[row]
        lo, hi, row = lo[use], hi[use], row[use]
        a, b, size, keep = self.named(data, lo, hi)
        with np.errstate(over="ignore"):
            h = mix(a ^ mix(b * np.uint64(3) + size))
        order, at = exact_runs(h, (a, b, size))
        one = order[at]
        keys, triple = h[one], (a[one], b[one], size[one])
        known = len(self.lens)
        met, code = np.zeros(len(keys), bool), np.zeros(len(keys), np.int64)
        if len(self.keys):
            place = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
            met = self.keys[place] == keys
            for mine, theirs in zip(triple, self.held, strict=True):
                met &= mine == theirs[place]
            code = np.where(met, self.codes[place], 0)
        flat, lens, fresh = self.flat, self.lens, np.flatnonzero(~met)
        if len(fresh):
            body = data.tobytes()
            ids, n = self.made([body[i:j] for i, j in zip(lo[one[fresh]].tolist(), hi[one[fresh]].tolist(), strict=True)])
            code[fresh] = known + np.arange(len(fresh))
            flat, lens = np.concatenate([flat, ids]), np.concatenate([lens, n])
            if known < MEMO and keep:  # once full it keeps the pieces met first, the frequent ones among them
                merged = np.concatenate([self.keys, keys[fresh]])
                by = np.argsort(merged)
                self.keys, self.codes = merged[by], np.concatenate([self.codes, code[fresh]])[by]
                self.held = tuple(np.concatenate([x, y[fresh]])[by] for x, y in zip(self.held, triple, strict=True))
                self.flat, self.lens = flat, lens
        begin = np.cumsum(lens) - lens
        code = code[run_of(order, at)]
        n = lens[code]
        ids = flat[gather(begin[code], n)]
        sizes = np.bincount(row, n, minlength=len(texts.lens)).astype(np.int64)
        if slow.any():
            parts = np.split(ids, np.cumsum(sizes)[:-1])
            at = np.flatnonzero(slow)
            for i, e in zip(at.tolist(), self.whole([t.as_py() for t in column.take(pa.array(at))]), strict=True):
                parts[i], sizes[i] = e, len(e)
            ids = np.concatenate(parts)
        return ids, sizes
