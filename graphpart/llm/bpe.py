"""Byte-pair encoding and decoding with content-defined chunk reuse.

A rolling hash over the last 24 characters cuts each text into chunks wherever its value ends in zeros, so equal passages
give equal chunks in whatever document they stand. A chunk is encoded once and kept. Its encoding is certain between
its first and last safe point (a space before a visible character, where the vocabulary's pattern always cuts); what
lies around a chunk join, from the last safe point on the left to the first on the right, is encoded again as one string,
after which the whole agrees with an encoding of the undivided text. Decoding maps ids back to bytes.

Edge cases: a null text is empty and gives no ids; special strings in a text become their one id, as the library does it;
texts of any length are encoded whole; repeated rows give equal digests; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import re
import struct
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from graphpart.llm.common import ID, TEXT, arrow_map, strings
from graphpart.llm.tokens import LETTERS, NUMBERS, SPACES, byte_of_char

WINDOW, CUT_BITS = 24, 9
MOST_PIECES, MOST_CHUNK_CHARS = 500_000, 16_000_000
BASE = 0x9E3779B97F4A7C15 | 1
_SAFE = re.compile(f" (?=[^{SPACES}])")
_UNSAFE = re.compile(f" [{SPACES}]")
_LATIN = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d| ?[{LETTERS}]+| ?[{NUMBERS}]+| ?[^\t-\r \x85\xa0{LETTERS}{NUMBERS}]+|[\t-\r \x85\xa0]+(?![^\t-\r \x85\xa0])|[\t-\r \x85\xa0]+")


@lru_cache(maxsize=4)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of BASE and of its inverse, modulo 2^64."""
    up, down = np.full(n, BASE, np.uint64), np.full(n, pow(BASE, -1, 1 << 64), np.uint64)
    up[0] = down[0] = 1
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


def content_cuts(text: str) -> list[int]:
    """Positions where the rolling (polynomial, modulo 2^64) hash of the WINDOW characters before has its top bits zero."""
    c = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    cuts: list[int] = []
    block = 1 << 15
    for lo in range(0, c.size, block):  # blocks overlap by a window, so cuts depend on the content alone
        part = c[max(0, lo - WINDOW) : lo + block]
        if part.size <= WINDOW:
            continue
        up, down = _powers(block + 2 * WINDOW)
        total = np.zeros(part.size + 1, np.uint64)
        np.cumsum(part.astype(np.uint64) * up[: part.size], out=total[1:])
        h = (total[WINDOW:] - total[: total.size - WINDOW]) * down[: total.size - WINDOW]
        h = (h ^ h >> np.uint64(29)) * np.uint64(0xBF58476D1CE4E5B9)
        cuts += (np.flatnonzero(h >> np.uint64(64 - CUT_BITS) == 0) + max(0, lo - WINDOW) + WINDOW).tolist()
    return sorted({x for x in cuts if 0 < x < c.size})


def packed(ids: list[int]) -> bytes:
    return struct.pack(f"<{len(ids)}I", *ids)


class ByteVocabulary(dict):
    """Piece (what follows a safe space) -> its ids as bytes of unsigned 32-bit integers."""

    def __init__(self, path: str) -> None:
        super().__init__()
        import tiktoken
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self._special = re.compile("(" + "|".join(map(re.escape, self.special)) + ")")
        char = byte_of_char()
        ranks = {bytes(char[c] for c in t): i for t, i in spec["model"]["vocab"].items() if t not in self.special}
        self.token_bytes = [b""] * (max([*ranks.values(), *self.special.values()]) + 1)
        for b, i in ranks.items():
            self.token_bytes[i] = b
        for t, i in self.special.items():
            self.token_bytes[i] = t.encode()
        self.core = tiktoken.Encoding("byte", pat_str=".", mergeable_ranks=ranks, special_tokens={})._core_bpe
        self.kept: dict[str, tuple[str, bytes, str]] = {}
        self.kept_chars = 0

    def _ids(self, text: str) -> bytes:
        try:
            text.encode("latin-1")
        except UnicodeEncodeError:
            return packed(self.library.encode(text, add_special_tokens=False).ids)
        one = self.core.encode_single_piece
        return packed([i for p in _LATIN.findall(text) for i in one(p.encode())])

    def __missing__(self, piece: str) -> bytes:
        if piece.isascii() and piece.isalpha():
            ids = packed(self.core.encode_single_piece(b" " + piece.encode()))
        else:
            ids = self._ids(" " + piece)
        if len(piece) <= 256:
            if len(self) >= MOST_PIECES:
                self.clear()
            self[piece] = ids
        return ids

    def span_ids(self, text: str) -> bytes:
        """Ids of a string that begins at a pattern boundary and ends before one (or is a whole text)."""
        if not text:
            return b""
        first, *pieces = _SAFE.split(text) if _UNSAFE.search(text) or text[-1] == " " else text.split(" ")
        return (self._ids(first) if first else b"") + b"".join(map(self.__getitem__, pieces))

    def chunk(self, text: str) -> tuple[str, bytes, str]:
        """(before the first safe point, ids between first and last, from the last on); without one, all is 'before'."""
        if (got := self.kept.get(text)) is None:
            first = _SAFE.search(text)
            if first is None:
                got = (text, b"", "")
            else:
                last = text.rfind(" ", 0, len(text) - 1)
                while not _SAFE.match(text, last):
                    last = text.rfind(" ", 0, last)
                got = (text[: first.start()], self.span_ids(text[first.start() : last]), text[last:])
            if self.kept_chars > MOST_CHUNK_CHARS:
                self.kept.clear()
                self.kept_chars = 0
            self.kept[text] = got
            self.kept_chars += len(text) + 4 * len(got[1])
        return got

    def encode(self, text: str) -> bytes:
        """Ids of the whole text, as little-endian unsigned 32-bit integers."""
        if "<|" in text and self._special.search(text):
            return b"".join(self.special[p].to_bytes(4, "little") if i % 2 else self.encode(p) for i, p in enumerate(self._special.split(text)))
        out, open_, at = [], "", 0
        for cut in (*content_cuts(text), len(text)):
            head, body, tail = self.chunk(text[at:cut])
            at = cut
            if tail:
                out += (self.span_ids(open_ + head), body)
                open_ = tail
            else:
                open_ += head
        out.append(self.span_ids(open_))
        return b"".join(out)

    def decode(self, ids: np.ndarray) -> bytes:
        return b"".join(map(self.token_bytes.__getitem__, ids.tolist()))


@lru_cache(maxsize=2)
def byte_vocabulary(path: str) -> ByteVocabulary:
    return ByteVocabulary(path)


def encode_documents(docs: DataFrame, path: str, keep_ids: bool = False) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256[, ids binary]); a map, no shuffle. Decoding starts from the ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = byte_vocabulary(path)
        for batch in batches:
            for part in (batch.slice(i, 512) for i in range(0, batch.num_rows, 512)):
                cols: list[list] = [[], [], [], []]
                for text in strings(part, TEXT):
                    ids = vocabulary.encode(text)
                    # bytes that are no UTF-8 come back as replacement characters, as in the library
                    text_again = vocabulary.decode(np.frombuffer(ids, "<u4")).decode("utf-8", "replace")
                    for col, x in zip(cols, (len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(text_again.encode()).hexdigest(), ids), strict=True):
                        col.append(x)
                arrays = [part.column(0), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.string())]
                names = [ID, "n_tokens", "ids_sha256", "decoded_sha256"]
                if keep_ids:
                    arrays.append(pa.array(cols[3], pa.binary()))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(arrays, names=names)

    return arrow_map(docs.select(ID, TEXT), run, f"{ID} {docs.schema[ID].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids binary" * keep_ids)


def decode_ids(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) from (doc_id, ids binary)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = byte_vocabulary(path)
        for batch in batches:
            texts = [vocabulary.decode(np.frombuffer(x or b"", "<u4")).decode("utf-8", "replace") for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=[ID, TEXT])

    return arrow_map(encoded.select(ID, "ids"), run, f"{ID} {encoded.schema[ID].dataType.simpleString()}, {TEXT} string")
