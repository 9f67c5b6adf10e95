"""Token counts: a prefix table holds the exact token count at every prefix, so truncation and budget questions need no re-encoding.

White space never enters a token of the word vocabulary, so counts add up over white-space separated chunks: the table
of a text is the running sum of its chunks' last cells. Inside a chunk, one forward pass of dynamic programming gives the
count of each prefix: its encoding ends in exactly one token, which must follow the last token of a shorter prefix. The
count of a text is the last cell of its table. Chunks are memoised in a bounded table, as are the pairs of tokens that
may stand side by side; time is linear in a chunk's length.

Edge cases: a null text is empty and has 0 tokens; special strings in a text count as the one token the library makes of
them; texts of any length are counted whole; repeated rows give equal counts; extra columns are ignored.
"""

from __future__ import annotations

import json
import re
import unicodedata
from array import array
from collections.abc import Iterator
from functools import cached_property, lru_cache
from itertools import islice, repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from graphpart.llm.common import ID, TEXT, arrow_map, strings

END = b"\xff"  # marks a word's end; never part of UTF-8
MOST_CHUNKS, MOST_IDS, LONG_CHUNK = 800_000, 6_000_000, 256
#: The white space of Unicode; letters and numbers below U+0100.
SPACES = "\t\n\x0b\x0c\r \x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"
LETTERS, NUMBERS = "a-zA-Z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff", "0-9\xb2\xb3\xb9\xbc-\xbe"
_CHUNK = re.compile(f"[^{SPACES}]+")
_PIECE = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{LETTERS}]+|[{NUMBERS}]|[^{LETTERS}{NUMBERS}]+")
_PYTHON_ONLY = re.compile("[\x1c-\x1f]")  # str.split() cuts here, the vocabulary's pattern doesn't
TOGETHER = 1 << 22  # characters whose chunks are numbered at once


def byte_of_char() -> dict[str, int]:
    """The printable stand-in of each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class WordVocabulary(dict):
    """Chunk -> number; ``start``, ``size`` and ``flat`` give the ids of a number. Ids equal the library's for the file."""

    __hash__ = object.__hash__

    def __init__(self, path: str) -> None:
        super().__init__()
        import tiktoken
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self._special = re.compile("(" + "|".join(map(re.escape, self.special)) + ")")
        vocab, char = spec["model"]["vocab"], byte_of_char()
        data: dict[str, bytes] = {}
        for c, b in char.items():
            data[c] = bytes([b])
            data[c + "</w>"] = bytes([b]) + END
        for a, b in spec["model"]["merges"]:
            data.setdefault(a + b, data[a] + data[b])
        ranks = {data[t]: i for t, i in vocab.items() if t in data}
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.longest = max(map(len, ranks))
        self.ranks = ranks
        self.core = tiktoken.Encoding("word", pat_str=".", mergeable_ranks=ranks, special_tokens={})._core_bpe
        self.reset()

    def reset(self) -> None:
        self.clear()
        self.flat, self.size, self.start = array("H"), array("q"), array("q")

    def piece_ids(self, piece: str) -> list[int]:
        return self.core.encode_single_piece(piece.encode() + END)

    def _encode(self, chunk: str) -> list[int]:
        if not chunk.isascii():
            try:
                chunk.encode("latin-1")
            except UnicodeEncodeError:
                return self.library.encode(chunk, add_special_tokens=False).ids
        chunk = chunk.lower()
        if chunk.isalpha():
            return self.piece_ids(chunk)
        return [i for piece in _PIECE.findall(chunk) for i in self.piece_ids(piece)]

    def __missing__(self, chunk) -> int:
        ids = [chunk[0]] if type(chunk) is tuple else self._encode(chunk)
        k = len(self.size)
        self.start.append(len(self.flat))
        self.size.append(len(ids))
        self.flat.extend(ids)
        if len(chunk) <= LONG_CHUNK:
            self[chunk] = k
        return k

    def trim(self) -> None:
        """Call between batches: forget all chunks once there are too many."""
        if len(self.size) > MOST_CHUNKS or len(self.flat) > MOST_IDS:
            self.reset()

    def chunks(self, text: str) -> list:
        """The text's chunks as keys of this table; a special string is a key of its own."""
        if "<|" in text and self._special.search(text):
            return [c for i, part in enumerate(self._special.split(text)) for c in ([(self.special[part],)] if i % 2 else self.chunks(part))]
        try:
            text.encode("latin-1")
            text = text.lower()
        except UnicodeEncodeError:
            pass
        return _CHUNK.findall(text) if _PYTHON_ONLY.search(text) else text.split()

    def numbers(self, text: str) -> np.ndarray:
        chunks = self.chunks(text)
        return np.fromiter(map(self.__getitem__, chunks), np.int64, len(chunks))

    @cached_property
    def spaced(self):
        """The merges with a space, which no chunk holds, for a word's end; so many words make one valid string."""
        import tiktoken

        ranks = {data[:-1] + b" " if data.endswith(END) else data: i for data, i in self.ranks.items() if b" " not in data}
        return tiktoken.Encoding("words", pat_str="[^ ]+ ", mergeable_ranks=ranks, special_tokens={})._core_bpe

    @cached_property
    def ends(self) -> np.ndarray:
        """By token id: does a word end there?"""
        out = np.zeros(1 << 16, bool)
        out[[i for i, data in self.bytes_of.items() if data.endswith(END)]] = True
        return out

    def _learn(self, chunks: list[str]) -> np.ndarray:
        """Numbers of distinct new chunks of lower-cased characters below U+0100, all encoded in one call."""
        pieces, counts = chunks.copy(), np.ones(len(chunks), np.int64)
        for i in [i for i, c in enumerate(chunks) if not c.isalpha()]:
            c = chunks[i]
            found = (c[:-1], c[-1]) if c[:-1].isalpha() else _PIECE.findall(c)
            pieces[i], counts[i] = " ".join(found), len(found)
        ids = np.frombuffer(self.spaced.encode_to_tiktoken_buffer(" ".join([*pieces, ""]), set()), np.uint32)
        end = np.r_[0, np.flatnonzero(self.ends[ids]) + 1]  # of pieces
        at = end[np.r_[0, np.cumsum(counts)]]  # of chunks
        numbers = np.arange(len(self.size), len(self.size) + len(chunks))
        self.start.frombytes((at[:-1] + len(self.flat)).tobytes())
        self.size.frombytes(np.diff(at).tobytes())
        self.flat.frombytes(ids.astype(np.uint16).tobytes())
        self.update(zip(chunks, numbers.tolist(), strict=True))
        for c in [c for c in chunks if len(c) > LONG_CHUNK]:
            del self[c]
        return numbers

    def _plain(self, text: str) -> bool:
        """Only characters below U+0100, no special string, and white space where Python sees it."""
        if not text.isascii():
            try:
                text.encode("latin-1")
            except UnicodeEncodeError:
                return False
        return not any(c in text for c in "\x1c\x1d\x1e\x1f") and not ("<|" in text and self._special.search(text))

    def _numbers_of_plain(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        split = pc.utf8_split_whitespace if any(c in t for t in texts for c in "\x85\xa0") else pc.ascii_split_whitespace
        parts = split(pa.array([t.lower() for t in texts], pa.string()))  # white space at the ends gives empty chunks, of no ids
        coded = parts.flatten().dictionary_encode()
        n = len(coded.dictionary)
        chunks = pc.binary_join(pa.ListArray.from_arrays(pa.array([0, n], pa.int32()), coded.dictionary), " ")[0].as_py().split(" ") if n else []
        number = np.fromiter(map(self.get, chunks, repeat(-1)), np.int64, n)
        new = np.flatnonzero(number < 0)
        number[new] = self._learn([chunks[i] for i in new.tolist()])
        return number[coded.indices.to_numpy()], np.diff(parts.offsets.to_numpy())

    def numbers_of(self, texts: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """For some texts at a time: the numbers of their chunks, one text after the other, and how many each has; an empty chunk
        has a number, too. What was told before is forgotten with ``trim``, which is called here.
        """
        lo = 0
        while lo < len(texts):
            hi, room = lo + 1, TOGETHER - len(texts[lo])
            while hi < len(texts) and len(texts[hi]) <= room:
                room -= len(texts[hi])
                hi += 1
            self.trim()
            some = texts[lo:hi]
            lo = hi
            plain = [self._plain(t) for t in some]
            if all(plain):
                yield self._numbers_of_plain(some)
                continue
            numbers, counts = self._numbers_of_plain([t for t, p in zip(some, plain, strict=True) if p])
            easy = iter(np.split(numbers, np.cumsum(counts)[:-1]))
            each = [next(easy) if p else self.numbers(t) for t, p in zip(some, plain, strict=True)]
            yield np.concatenate(each), np.array([x.size for x in each])

    def sizes(self) -> np.ndarray:
        return np.frombuffer(self.size, np.int64) if self.size else np.zeros(0, np.int64)

    def ids(self, numbers: np.ndarray) -> np.ndarray:
        """The ids of a sequence of chunk numbers, as uint16."""
        if not numbers.size:
            return np.zeros(0, np.uint16)
        n = self.sizes()[numbers]
        end = np.cumsum(n)
        at = np.repeat(np.frombuffer(self.start, np.int64)[numbers] - (end - n), n) + np.arange(int(end[-1]))
        return np.frombuffer(self.flat, np.uint16)[at]


CONTRACTIONS = frozenset(("'s", "'t", "'re", "'ve", "'m", "'ll", "'d"))


class PrefixCounts(dict):
    """Chunk -> the last cell of its prefixes' counts; ``chunk`` gives all cells, for the chunk that a budget ends in.

    A piece of a chunk (what the vocabulary's pattern cuts) is one forward pass over its bytes: the encoding of a prefix ends
    in the one token that may follow the last token of the shorter prefix before it. Which tokens may stand side by side
    is kept in a bounded table.
    """

    __hash__ = object.__hash__

    def __init__(self, vocabulary: WordVocabulary) -> None:
        super().__init__()
        self.vocabulary = vocabulary
        open_ids = {data: i for data, i in vocabulary.ranks.items() if not data.endswith(END)}
        closed = {data[:-1]: i for data, i in vocabulary.ranks.items() if data.endswith(END)}
        #: bytes -> the token of them within a word and at a word's end, -1 for none; so for all that tokens end in
        self.tokens: dict[bytes, tuple[int, int]] = {}
        for data in open_ids.keys() | closed.keys():
            for i in range(len(data)):
                tail = data[i:]
                self.tokens.setdefault(tail, (open_ids.get(tail, -1), closed.get(tail, -1)))
        self.beside: dict[int, bool] = {}

    def trim(self) -> None:
        if len(self) > MOST_CHUNKS:
            self.clear()
        if len(self.beside) > MOST_CHUNKS:
            self.beside.clear()

    def _fits(self, left: int, right: int) -> bool:
        v = self.vocabulary
        known = self.beside[left << 17 | right] = v.core.encode_single_piece(v.bytes_of[left] + v.bytes_of[right]) == [left, right]
        return known

    def piece(self, piece: str, every: bool = True) -> list[int]:
        """Counts of the prefixes of 1, 2, ... characters of a piece, each closed as a word; the last one alone without ``every``."""
        data = piece.encode()
        n, known, beside, fits = len(data), self.tokens.get, self.beside.get, self._fits
        last, steps = [-1] * (n + 1), [0] * (n + 1)
        out = []
        for to in range(1, n + 1):
            ends = to == n or every and data[to] & 0xC0 != 0x80  # a character ends here
            inner = to < n
            for lo in range(to - 1, -1, -1):
                found = known(data[lo:to])
                if found is None:  # no token ends in that
                    break
                left = last[lo]
                if lo and left < 0:
                    continue
                opened, closed = found
                if ends and closed >= 0:
                    ok = not lo or beside(left << 17 | closed)
                    if ok or ok is None and fits(left, closed):
                        out.append(steps[lo] + 1)
                        ends = False
                if inner and opened >= 0:
                    ok = not lo or beside(left << 17 | opened)
                    if ok or ok is None and fits(left, opened):
                        last[to], steps[to] = opened, steps[lo] + 1
                        inner = False
                if not ends and not inner:
                    break
        return out

    def _joined(self, pieces: list[str]) -> list[int]:
        out: list[int] = []
        total = 0
        for piece in pieces:
            if piece in CONTRACTIONS:  # cut, it is an apostrophe and a letter
                apostrophe = self.piece("'")[0]
                out.append(total + apostrophe)
                if len(piece) == 3:
                    out.append(total + apostrophe + self.piece(piece[1])[0])
                total += self.piece(piece)[-1]
                out.append(total)
            else:
                out += [total + n for n in self.piece(piece)] if total else self.piece(piece)
                total = out[-1]
        return out

    def _pieces(self, chunk: str) -> list[str] | None:
        """Pieces of a chunk of characters below U+0100, lower-cased; None for others."""
        try:
            chunk.encode("latin-1")
        except UnicodeEncodeError:
            return None
        low = chunk.lower()
        return [low] if low.isascii() and low.isalpha() else _PIECE.findall(low)

    def chunk(self, chunk: str) -> list[int]:
        """Counts of the prefixes of 1, 2, ... characters of a chunk."""
        pieces = self._pieces(chunk)
        return self._of_any(chunk) if pieces is None else self._joined(pieces)

    def _of_any(self, chunk: str) -> list[int]:
        """As ``chunk``; the library normalises and cuts. Where a prefix isn't normalised as the chunk is (a mark that joins the
        letter before), the run it ends in is encoded anew.
        """
        library = self.vocabulary.library
        whole, parts = self._runs(chunk)
        cells = [0, *self._joined([whole[a:b] for a, b in parts])]
        if len(cells) != len(whole) + 1:  # a character that the pattern leaves out
            return [len(library.encode(chunk[:i], add_special_tokens=False).ids) for i in range(1, len(chunk) + 1)]
        if len(whole) == len(chunk) and unicodedata.is_normalized("NFC", chunk) and all(len(c.lower()) == 1 for c in chunk):
            return cells[1:]
        starts = [0] * (len(whole) + 1)
        for a, b in parts:
            starts[a + 1 : b + 1] = [a] * (b - a)
        out, safe, before = [], 0, 0  # chunk[:safe] is normalised to whole[:before], whatever follows
        for i, c in enumerate(chunk):
            if i and not unicodedata.combining(c):
                here = library.normalizer.normalize_str(chunk[safe:i])
                if library.normalizer.normalize_str(chunk[safe : i + 1]) == here + library.normalizer.normalize_str(c):
                    safe, before = i, before + len(here)
            tail = library.normalizer.normalize_str(chunk[safe : i + 1])
            at = before + len(tail)
            if whole[before:at] == tail:
                out.append(cells[at])
            else:
                a = starts[before]
                out.append(cells[a] + len(library.encode(whole[a:before] + tail, add_special_tokens=False).ids))
        return out

    def _runs(self, chunk: str) -> tuple[str, list[tuple[int, int]]]:
        """The chunk as the library normalises it, and the pieces it cuts that into."""
        whole = self.vocabulary.library.normalizer.normalize_str(chunk)
        return whole, [span for _, span in self.vocabulary.library.pre_tokenizer.pre_tokenize_str(whole)]

    def __missing__(self, chunk) -> int:
        if type(chunk) is tuple:
            total = 1
        else:
            pieces = self._pieces(chunk)
            if pieces is None:
                whole, spans = self._runs(chunk)
                pieces = [whole[a:b] for a, b in spans]
            total = sum(self.piece(p, every=False)[-1] for p in pieces)
        if len(chunk) <= LONG_CHUNK:
            self[chunk] = total
        return total


class PrefixTable:
    """Exact counts of all prefixes of one text: ``count(i)`` for text[:i], ``truncate(budget)`` for the longest that fits."""

    def __init__(self, counts: PrefixCounts, text: str) -> None:
        self.counts, self.vocabulary, self.text = counts, counts.vocabulary, text
        chunks = counts.vocabulary.chunks(text)
        self.totals = np.zeros(len(chunks) + 1, np.int64)  # at the chunks' ends
        np.cumsum(np.fromiter(map(counts.__getitem__, chunks), np.int64, len(chunks)), out=self.totals[1:])
        self.cells = lru_cache(maxsize=4)(counts.chunk)

    def spans(self) -> Iterator[tuple[int, int, bool]]:
        """(start, end, special) of each chunk, in order."""
        at = 0
        for i, part in enumerate(self.vocabulary._special.split(self.text)) if "<|" in self.text else [(0, self.text)]:
            if i % 2:
                yield at, at + len(part), True
            else:
                yield from ((m.start() + at, m.end() + at, False) for m in _CHUNK.finditer(part))
            at += len(part)

    def count(self, length: int | None = None) -> int:
        """The last cell within text[:length]."""
        if length is None or length >= len(self.text):
            return int(self.totals[-1])
        k = 0
        for start, end, _ in self.spans():
            if end > length:
                return int(self.totals[k]) + (self.cells(self.text[start:end])[length - start - 1] if start < length else 0)
            k += 1
        return int(self.totals[k])

    def truncate(self, budget: int) -> int:
        """Characters of the longest prefix of at most ``budget`` tokens."""
        if self.totals[-1] <= budget:
            return len(self.text)
        k = int(np.searchsorted(self.totals, budget, side="right")) - 1  # chunks that fit
        start, end, special = next(islice(self.spans(), k, None))
        return start + max((i for i, n in enumerate([] if special else self.cells(self.text[start:end]), 1) if self.totals[k] + n <= budget), default=0)


@lru_cache(maxsize=2)
def word_vocabulary(path: str) -> WordVocabulary:
    return WordVocabulary(path)


@lru_cache(maxsize=2)
def prefix_counts(path: str) -> PrefixCounts:
    return PrefixCounts(word_vocabulary(path))


def token_counts(docs: DataFrame, path: str, limit: int = 2048) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit, kept_chars): kept_chars is the longest prefix within the limit. A map, no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = prefix_counts(path)
        for batch in batches:
            n_bytes, n_tokens, kept = [], [], []
            for text in strings(batch, TEXT):
                counts.trim()
                table = PrefixTable(counts, text)
                n_bytes.append(len(text.encode()))
                n_tokens.append(table.count())
                kept.append(table.truncate(limit))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n_bytes, pa.int64()), pa.array(n_tokens, pa.int64()), pa.array([n > limit for n in n_tokens], pa.bool_()), pa.array(kept, pa.int64())],
                names=[ID, "n_bytes", "n_tokens", "over_limit", "kept_chars"],
            )

    return arrow_map(docs.select(ID, TEXT), run, f"{ID} {docs.schema[ID].dataType.simpleString()}, n_bytes long, n_tokens long, over_limit boolean, kept_chars long")
