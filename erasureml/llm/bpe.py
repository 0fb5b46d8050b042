"""Byte-level BPE with the tokenizers library over Arrow batches, and decoding by the reversed byte table.

A byte-level vocabulary writes every byte as one printable character; `byte_characters` is that mapping.  Encoding
gives ids and, on request, the character at which each token starts.  A token may end inside a character: its start is
the character that its first byte belongs to.  Decoding looks ids up in a table of byte strings; the bytes are joined
before they are read as UTF-8, so characters split over tokens come out whole, and `pieces` gives each character to the
token that completes it.  Bytes that aren't UTF-8 become U+FFFD in text; `decode_bytes` keeps them.

Texts over `cut` characters are encoded in parts that end before white space following another character, where the
pattern of the vocabulary always parts words, so memory is bounded.  Null and empty texts have no tokens.  Rows keep
their doc_id as it is: null ones and repeated ones are rows of their own.  Only doc_id and text are read and no other
column is returned, so none can clash.  An empty table gives no rows.
"""

from __future__ import annotations

import base64
import codecs
import hashlib
import json
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame, SparkSession

from erasureml.llm.core import Texts, few_rows, read_table
from erasureml.llm.pieces import BLANK, CLASS, DistinctCoder, gather

CUT = 100_000
BATCH_CHARS = 1_000_000
_SEAM = regex.compile(r"(?<=\S)(?=\s)")


def byte_characters() -> dict[int, str]:
    """Printable bytes stand for themselves; the others, in order, for the characters from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


@lru_cache(maxsize=4)
def tokenizer(path: str, plain: bool = True):
    """plain: the strings of special tokens in a text are ordinary text."""
    from tokenizers import Tokenizer

    found = Tokenizer.from_file(path)
    found.encode_special_tokens = plain
    return found


@lru_cache(maxsize=4)
def byte_table(path: str) -> tuple[bytes, ...]:
    """The bytes of every id."""
    with open(path, encoding="utf-8") as f:
        vocabulary = json.load(f)["model"]["vocab"]
    back = {c: b for b, c in byte_characters().items()}
    table = [b""] * (max(vocabulary.values()) + 1)
    for token, i in vocabulary.items():
        table[i] = bytes(back[c] for c in token) if all(c in back for c in token) else token.encode()
    return tuple(table)


def check_ranks(path: str, ranks: str) -> None:
    """Raise unless the ranks (base64 bytes and a number a line) are the ids of the vocabulary at `path`, and each of its
    merges gives the next rank."""
    with open(ranks, "rb") as f:
        wanted = {int(n): base64.b64decode(token) for token, n in map(bytes.split, f)}
    table = byte_table(path)
    with open(path, encoding="utf-8") as f:
        model = json.load(f)["model"]
    merged = [model["vocab"]["".join(m if isinstance(m, list) else m.split(" "))] for m in model["merges"]]
    if any(n >= len(table) or table[n] != token for n, token in wanted.items()) or merged != list(range(256, len(wanted))):
        raise ValueError(f"{path} doesn't hold the ranks of {ranks}")


def parts(text: str, cut: int = CUT) -> list[str]:
    """The text in parts of about `cut` characters that can be encoded one by one."""
    out, at = [], 0
    while len(text) - at > cut:
        seam = _SEAM.search(text, at + cut)
        if seam is None or seam.start() >= len(text):
            break
        out.append(text[at : seam.start()])
        at = seam.start()
    return [*out, text[at:]]


class ByteCoder(DistinctCoder):
    """Pieces of the byte-level pattern: runs of letters, of digits or of marks, each with one space before it if there is
    one, and what is left of white space.

    Words with a space go through the library many to a call, their ids parted at the tokens that begin with a space.
    """

    def __init__(self, path: str) -> None:
        super().__init__(tokenizer(path))
        self.spaced = np.array([t[:1] == b" " for t in byte_table(path)], bool)

    def part(self, texts: Texts, data: np.ndarray, lead: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        n, kind = len(data), CLASS[data]
        first = np.zeros(n + 1, bool)
        first[texts.starts] = True
        run = first[:-1] | np.concatenate([[True], kind[1:] != kind[:-1]])[:n]
        blank = kind == BLANK
        joins = np.flatnonzero(run & ~blank)  # runs that aren't blank
        before = joins[(joins > 0) & ~first[joins]] - 1  # the byte before them, if of the same text
        after_blank = before[blank[before]]
        cut = run.copy()
        cut[after_blank] = True
        cut[after_blank[data[after_blank] == 0x20] + 1] = False
        bounds = np.append(np.flatnonzero(cut), n)
        return data, bounds[:-1], bounds[1:]

    def made(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        many = np.array([len(p) > 1 and p[0] == 0x20 and p[1] != 0x20 for p in pieces], bool)
        words = [p.decode() for p, x in zip(pieces, many.tolist(), strict=True) if x]
        ids = [np.zeros(0, np.uint32)]
        for i in range(0, len(words), 10_000):
            part = words[i : i + 10_000]
            lines = ["".join(part[j : j + 100]) for j in range(0, len(part), 100)]
            ids += [np.array(e.ids, np.uint32) for e in self.full.encode_batch_fast(lines, add_special_tokens=False)]
        flat = np.concatenate(ids)
        begins = np.flatnonzero(self.spaced[flat])
        if len(begins) != len(words):
            raise ValueError("a spaced word doesn't begin with the only token of its that has a space")
        other = self.singly([p for p, x in zip(pieces, many.tolist(), strict=True) if not x])
        size = np.diff(np.append(begins, len(flat)))
        lens, first = np.empty(len(pieces), np.int64), np.empty(len(pieces), np.int64)
        lens[many], lens[~many] = size, other[1]
        first[many], first[~many] = begins, len(flat) + np.cumsum(other[1]) - other[1]
        return np.concatenate([flat, other[0]])[gather(first, lens)], lens

    def whole(self, texts: list[str]) -> list[np.ndarray]:
        own = [parts(t) for t in texts]
        ids = super().whole([p for x in own for p in x])
        ends = np.cumsum([len(x) for x in own]).tolist()
        return [np.concatenate(ids[i:j]) for i, j in zip([0, *ends[:-1]], ends, strict=True)]


@lru_cache(maxsize=2)
def byte_coder(path: str) -> ByteCoder:
    """Kept by a Python worker from task to task."""
    return ByteCoder(path)


def encode_texts(texts: pa.Array, path: str) -> Iterator[np.ndarray]:
    """The ids of each text."""
    lens = pc.fill_null(pc.utf8_length(texts), 0).to_numpy(zero_copy_only=False)
    total, lo = np.cumsum(lens), 0
    while lo < len(texts):
        hi = max(lo + 1, int(np.searchsorted(total, (total[lo - 1] if lo else 0) + BATCH_CHARS)))
        ids, sizes = byte_coder(path).encode(pc.fill_null(texts.slice(lo, hi - lo), ""))
        yield from np.split(ids, np.cumsum(sizes)[:-1])
        lo = hi


def decode_bytes(ids: np.ndarray, path: str) -> bytes:
    table = byte_table(path)
    return b"".join([table[i] for i in ids.tolist()])


def decode(ids: np.ndarray, path: str) -> str:
    return decode_bytes(ids, path).decode("utf-8", "replace")


def pieces(ids: np.ndarray, path: str) -> list[str]:
    """The text that each token completes; joined, they are the whole text."""
    reader, table = codecs.getincrementaldecoder("utf-8")("replace"), byte_table(path)
    out = [reader.decode(table[i]) for i in ids.tolist()]
    if out:
        out[-1] += reader.decode(b"", True)
    return out


def character_starts(ids: np.ndarray, text: str, path: str) -> np.ndarray:
    """For every token, the index of the character that its first byte belongs to."""
    table = byte_table(path)
    ends = np.cumsum([len(table[i]) for i in ids.tolist()], dtype=np.int64)
    first = np.concatenate([[0], ends[:-1]]).astype(np.int64) if len(ends) else ends
    data = np.frombuffer(text.encode(), np.uint8)
    return np.cumsum((data & 0xC0) != 0x80)[first] - 1 if len(first) else first


def encode(docs: DataFrame, path: str, offsets: bool = False) -> DataFrame:
    """docs' doc_id with ids (and starts, by character)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for lo, hi in slices(texts):
                ids = list(encode_texts(batch.column(1).slice(lo, hi - lo), path))
                out = {"doc_id": batch.column(0).slice(lo, hi - lo).cast(pa.int64()), "ids": lists(ids)}
                if offsets:
                    out["starts"] = lists([character_starts(i, t or "", path) for i, t in zip(ids, texts[lo:hi], strict=True)])
                yield pa.RecordBatch.from_pydict(out)

    return few_rows(docs).select("doc_id", "text").mapInArrow(run, "doc_id long, ids array<int>" + ", starts array<int>" * offsets)


def slices(texts: list[str | None]) -> Iterator[tuple[int, int]]:
    """Ranges of about BATCH_CHARS characters."""
    lo = size = 0
    for i, t in enumerate(texts):
        size += len(t or "")
        if size >= BATCH_CHARS:
            yield lo, i + 1
            lo, size = i + 1, 0
    if lo < len(texts):
        yield lo, len(texts)


def lists(arrays: list[np.ndarray]) -> pa.Array:
    ends = np.concatenate([[0], np.cumsum([len(a) for a in arrays])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.zeros(0, np.int32), *arrays]).astype(np.int32)))


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """Digests of the ids and of the bytes decoded from them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, coded, decoded = [], [], []
            for ids in encode_texts(batch.column(1), path):
                n.append(len(ids))
                coded.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
                decoded.append(hashlib.sha256(decode_bytes(ids, path)).hexdigest())
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0).cast(pa.int64()), "n_tokens": pa.array(n, pa.int64()), "ids_sha256": pa.array(coded, pa.string()), "decoded_sha256": pa.array(decoded, pa.string())})

    return few_rows(docs).select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def default_vocabulary() -> str:
    """byte_bpe_50k.json: the vocabulary of byte_bpe_50k.tiktoken in the form that the tokenizers library reads."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def default_ranks() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    check_ranks(default_vocabulary(), default_ranks())
    return round_trip(read_table(spark, sf_dir, "documents"), default_vocabulary())


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as ids, with the character at which each token starts."""
    return encode(docs, default_vocabulary(), offsets=True)
