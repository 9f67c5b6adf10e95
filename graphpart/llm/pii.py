"""Personal data: fixed patterns, and what a character-level bidirectional LSTM with CRF transitions adds to them.

The network is trained in numpy from labelled spans (a seeded generator of contacts in many written forms, often one right
after the other, with numbers that are none between them). So it finds what the patterns swallow, such as a card number
right behind a phone number, and forms they don't know. A text is read in windows of 64 characters every 24: a span of
up to 41 characters lies whole in some window. ``decode`` gives no span to a window without a digit or an at-sign, as every
kind of span holds one; such windows needn't be scored. Windows are decoded by Viterbi; their spans are put on the text's
own coordinates, overlapping ones of a kind are merged, those that fail the kind's check or touch a pattern's span go.

Edge cases: a null text is empty; texts of any length are read whole; equal texts get equal spans; extra columns are
ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from graphpart.llm.common import ID, TEXT, arrow_map, strings

KINDS = ("email", "ip", "card", "phone")
Span = tuple[int, int, int]  # kind, start, end
LENGTH, STRIDE, WINDOWS = 64, 24, 512
EMBED, HIDDEN = 8, 16
TAGS = 1 + 2 * len(KINDS)  # outside, then begin and inside of each kind

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_ANCHOR = re.compile(r"[0-9@]")
_NOT_DIGIT = re.compile(r"[^0-9]")


def luhn(digits: str) -> bool:
    total = sum(map(int, digits[-1::-2])) + sum(int(d) * 2 - 9 * (d > "4") for d in digits[-2::-2])
    return total % 10 == 0


def _emails(text: str) -> Iterator[tuple[int, int]]:
    free = 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            free = m.end()
        at = text.find("@", max(at + 1, free))


def _ip_ok(s: str) -> bool:
    return all(len(p := part.lstrip("0")) < 4 and int(p or 0) <= 255 for part in s.split("."))


def _card_ok(s: str) -> bool:
    digits = _NOT_DIGIT.sub("", s) if len(s) < 64 else ""
    return 16 <= len(digits) <= 19 and luhn(digits)


def _phone_ok(s: str) -> bool:
    return 8 <= len(_NOT_DIGIT.sub("", s)) <= 15


def base_spans(text: str) -> list[Span]:
    """What the fixed patterns find, by kind, then start."""
    out: list[Span] = [(0, a, b) for a, b in _emails(text)]
    for kind, pattern, ok in ((1, _IP, _ip_ok), (2, _CARD, _card_ok), (3, _PHONE, _phone_ok)):
        out += [(kind, m.start(), m.end()) for m in pattern.finditer(text) if ok(m[0])]
    return out


# -- the network

_PUNCT = "@.-_%+() \n:/,;='\"|#<>[]"
CLASSES = 26 + 1 + len(_PUNCT) + 2
_ANCHORS = (26, 27 + _PUNCT.index("@"))  # classes of digits and of the at-sign


def _class_table() -> np.ndarray:
    table = np.full(256, CLASSES - 1, np.int64)
    for i in range(256):
        c = chr(i)
        if c.isascii() and c.isalpha():
            table[i] = ord(c.lower()) - 97
        elif c.isascii() and c.isdigit():
            table[i] = 26
        elif c in _PUNCT:
            table[i] = 27 + _PUNCT.index(c)
        elif c.isalpha():
            table[i] = CLASSES - 2
    return table


_TABLE = _class_table()


def char_classes(text: str) -> np.ndarray:
    c = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    return np.where(c < 256, _TABLE[np.minimum(c, 255)], CLASSES - 2)


def _sig(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-x))


class Tagger:
    """Bidirectional LSTM emissions with CRF transitions; arrays are (time, batch, ...)."""

    def __init__(self, seed: int = 11) -> None:
        rng = np.random.default_rng(seed)
        self.p = {"E": rng.normal(0, 0.3, (CLASSES, EMBED)), "O": rng.normal(0, 0.2, (2 * HIDDEN, TAGS)), "b": np.zeros(TAGS), "T": rng.normal(0, 0.1, (TAGS, TAGS)), "S": np.zeros(TAGS)}
        for d in "FB":
            self.p["W" + d] = rng.normal(0, 0.3, (EMBED + HIDDEN, 4 * HIDDEN))
            self.p["c" + d] = np.r_[np.zeros(HIDDEN), np.ones(HIDDEN), np.zeros(2 * HIDDEN)]

    def _lstm(self, x: np.ndarray, d: str, keep: bool) -> tuple[np.ndarray, list]:
        w, c0, steps = self.p["W" + d], self.p["c" + d], []
        pre = x @ w[:EMBED] + c0
        h = c = np.zeros((x.shape[1], HIDDEN))
        out = np.empty((*x.shape[:2], HIDDEN))
        for t in range(len(x)) if d == "F" else range(len(x) - 1, -1, -1):
            z = pre[t] + h @ w[EMBED:]
            s = _sig(z[:, : 3 * HIDDEN])
            i, f, o, g = s[:, :HIDDEN], s[:, HIDDEN : 2 * HIDDEN], s[:, 2 * HIDDEN :], np.tanh(z[:, 3 * HIDDEN :])
            was, c = c, f * c + i * g
            th = np.tanh(c)
            if keep:
                steps.append((t, h, was, i, f, o, g, th))
            h = o * th
            out[t] = h
        return out, steps

    def emissions(self, classes: np.ndarray, keep: bool = False):
        x = self.p["E"][classes]
        (hf, sf), (hb, sb) = self._lstm(x, "F", keep), self._lstm(x, "B", keep)
        both = np.concatenate([hf, hb], axis=2)
        e = both @ self.p["O"] + self.p["b"]
        return (e, x, both, sf, sb) if keep else e

    def _lstm_back(self, x: np.ndarray, steps: list, dout: np.ndarray, d: str, grad: dict) -> np.ndarray:
        w = self.p["W" + d]
        dx, dh, dc = np.zeros_like(x), np.zeros((x.shape[1], HIDDEN)), np.zeros((x.shape[1], HIDDEN))
        gw, gc = np.zeros_like(w), np.zeros(4 * HIDDEN)
        for t, h, was, i, f, o, g, th in reversed(steps):
            dh = dh + dout[t]
            dc = dc + dh * o * (1 - th * th)
            dz = np.concatenate([dc * g * i * (1 - i), dc * was * f * (1 - f), dh * th * o * (1 - o), dc * i * (1 - g * g)], axis=1)
            gw[:EMBED] += x[t].T @ dz
            gw[EMBED:] += h.T @ dz
            gc += dz.sum(0)
            dx[t], dh, dc = dz @ w[:EMBED].T, dz @ w[EMBED:].T, dc * f
        grad["W" + d], grad["c" + d] = gw, gc
        return dx

    def loss_and_gradient(self, classes: np.ndarray, tags: np.ndarray) -> tuple[float, dict]:
        e, x, both, sf, sb = self.emissions(classes, keep=True)
        t_, n = classes.shape
        trans, start = self.p["T"], self.p["S"]
        a, b = np.empty_like(e), np.zeros_like(e)
        lse = lambda v, axis: (m := v.max(axis=axis, keepdims=True)).squeeze(axis) + np.log(np.exp(v - m).sum(axis=axis))
        a[0] = e[0] + start
        for t in range(1, t_):
            a[t] = e[t] + lse(a[t - 1][:, :, None] + trans, 1)
        for t in range(t_ - 2, -1, -1):
            b[t] = lse(trans[None] + (e[t + 1] + b[t + 1])[:, None, :], 2)
        z = lse(a[-1], 1)
        idx = np.arange(n)
        gold = start[tags[0]] + sum(e[t, idx, tags[t]] for t in range(t_)) + sum(trans[tags[t - 1], tags[t]] for t in range(1, t_))
        de = np.exp(a + b - z[:, None])
        grad: dict[str, np.ndarray] = {"T": np.zeros_like(trans), "S": de[0].sum(0)}
        for t in range(1, t_):
            grad["T"] += np.exp(a[t - 1][:, :, None] + trans + (e[t] + b[t])[:, None, :] - z[:, None, None]).sum(0)
            np.add.at(grad["T"], (tags[t - 1], tags[t]), -1)
        np.add.at(grad["S"], tags[0], -1)
        for t in range(t_):
            de[t, idx, tags[t]] -= 1
        flat = de.reshape(-1, TAGS)
        grad["O"], grad["b"] = both.reshape(-1, 2 * HIDDEN).T @ flat, flat.sum(0)
        dboth = de @ self.p["O"].T
        dx = self._lstm_back(x, sf, dboth[:, :, :HIDDEN], "F", grad) + self._lstm_back(x, sb, dboth[:, :, HIDDEN:], "B", grad)
        grad["E"] = np.zeros_like(self.p["E"])
        np.add.at(grad["E"], classes, dx)
        return float((z - gold).mean()), {k: g / n for k, g in grad.items()}

    def fit(self, batches: Iterator[tuple[np.ndarray, np.ndarray]], rate: float = 0.03) -> list[float]:
        m, v, losses = {}, {}, []
        for step, (classes, tags) in enumerate(batches, 1):
            loss, grad = self.loss_and_gradient(classes, tags)
            losses.append(loss)
            for k, g in grad.items():
                g = np.clip(g, -5, 5)
                m[k] = 0.9 * m.get(k, 0) + 0.1 * g
                v[k] = 0.99 * v.get(k, 0) + 0.01 * g * g
                self.p[k] = self.p[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)
        return losses

    def decode(self, classes: np.ndarray) -> np.ndarray:
        """Viterbi tags (time, batch); an inside tag may only follow its own begin or inside, and a window without an anchor is
        outside throughout.
        """
        e = self.emissions(classes)
        bar = np.zeros((TAGS, TAGS))
        for k in range(len(KINDS)):
            bar[:, 2 + 2 * k] = -1e9
            bar[[1 + 2 * k, 2 + 2 * k], 2 + 2 * k] = 0
        trans = self.p["T"] + bar
        best, back = e[0] + self.p["S"] + np.minimum(bar[0], 0), []
        for t in range(1, len(e)):
            step = best[:, :, None] + trans
            back.append(step.argmax(1))
            best = step.max(1) + e[t]
        tags = np.empty(classes.shape, np.int64)
        tags[-1] = best.argmax(1)
        for t in range(len(e) - 2, -1, -1):
            tags[t] = back[t][np.arange(classes.shape[1]), tags[t + 1]]
        return np.where(np.isin(classes, _ANCHORS).any(axis=0), tags, 0)


def labelled_windows(rng: np.random.Generator, n: int) -> tuple[np.ndarray, np.ndarray]:
    """n windows of made-up prose holding contacts in many forms, and numbers that are none; (time, batch) classes and tags."""
    digits = lambda k: "".join(map(str, rng.integers(0, 10, k)))
    word = lambda: "".join("abcdefghijklmnopqrstuvwxyz\xe9\xfc"[c] for c in rng.integers(0, 28, rng.integers(1, 9)))

    def card() -> str:
        d = digits(15)
        d += next(x for x in "0123456789" if luhn(d + x))
        return rng.choice(["", " ", "-", "."]).join([d[i : i + 4] for i in range(0, 16, 4)])

    def item() -> tuple[int, str]:
        kind = int(rng.integers(-2, 4))
        if kind == 0:
            return 0, f"{word()}{rng.choice(['.', '_', '', '-'])}{digits(int(rng.integers(0, 3)))}@{word()}{rng.choice(['.', '.mail.', '-x.', ' . '])}{rng.choice(['com', 'org', 'net', 'de', 'fr'])}"
        if kind == 1:
            return 1, rng.choice([".", ".", " . ", "-"]).join(str(x) for x in rng.integers(0, 256, 4))
        if kind == 2:
            return 2, card()
        if kind == 3:
            a, b, c = digits(3), digits(3), digits(4)
            return 3, str(rng.choice([f"+1 ({a}) {b}-{c}", f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"{a}.{b}.{c}", f"+{digits(2)} {a} {b}{c}", f"00{digits(2)} {a} {b} {c}"]))
        return -1, str(rng.choice([f"{digits(4)}-{digits(2)}-{digits(2)}", digits(int(rng.integers(1, 6))), f"{digits(2)}.{digits(2)}", f"{digits(1)}.{digits(1)}.{digits(2)}", f"{digits(2)}:{digits(2)}", f"{digits(3)} {word()}", f"{word()}{digits(3)}", f"#{digits(6)}"]))

    classes, tags = np.empty((LENGTH, n), np.int64), np.zeros((LENGTH, n), np.int64)
    for j in range(n):
        text, marks = "", []
        for _ in range(int(rng.integers(0, 8))):
            text += word() + rng.choice([" ", " ", ", ", ". ", "\n"])
        while len(text) < LENGTH + 8:
            kind, s = item()
            marks.append((kind, len(text), len(text) + len(s)))
            text += s + rng.choice([" ", " ", ". ", ", ", "\n"])
            for _ in range(int(rng.integers(0, 6)) if rng.random() < 0.6 else 0):  # often the next one follows at once
                text += word() + " "
        cut = int(rng.integers(0, len(text) - LENGTH + 1))
        classes[:, j] = char_classes(text[cut : cut + LENGTH])
        for kind, a, b in marks:
            if kind >= 0 and b > cut and a < cut + LENGTH:
                lo, hi = max(a, cut) - cut, min(b, cut + LENGTH) - cut
                tags[lo:hi, j] = 2 + 2 * kind
                if a >= cut:
                    tags[lo, j] = 1 + 2 * kind
                else:
                    tags[lo, j] = 1 + 2 * kind  # a span cut off by the window's edge begins there
    return classes, tags


@lru_cache(maxsize=2)
def train_tagger(steps: int = 420, batch: int = 32, pool: int = 6000, seed: int = 5) -> Tagger:
    """Seeded, so every driver trains the same network; some 30 seconds, once a process."""
    rng, tagger = np.random.default_rng(seed), Tagger()
    classes, tags = labelled_windows(rng, pool)
    tagger.fit((classes[:, at], tags[:, at]) for at in (rng.choice(pool, batch, replace=False) for _ in range(steps)))
    return tagger


# -- windows, merged on the text's own coordinates


def _plausible(kind: int, s: str) -> bool:
    digits = _NOT_DIGIT.sub("", s)
    if kind == 0:
        return bool(re.fullmatch(r"[^\s@]+\s?@\s?[A-Za-z0-9-]+(?:\s?\.\s?[A-Za-z0-9-]+)+", s))
    if kind == 1:
        parts = re.fullmatch(r"([0-9]+)\s?[.-]\s?([0-9]+)\s?[.-]\s?([0-9]+)\s?[.-]\s?([0-9]+)", s)
        return bool(parts) and all(len(p) <= 3 and int(p) <= 255 for p in parts.groups())
    if kind == 2:
        return 16 <= len(digits) <= 19 and luhn(digits) and bool(re.fullmatch(r"[0-9 .-]+", s))
    return 10 <= len(digits) <= 15 and bool(re.fullmatch(r"[+(]?[0-9][0-9 ().-]*[0-9]", s)) and bool(re.search(r"[ ().-]", s))


def window_starts(anchors: list[int], n: int) -> list[int]:
    """Starts of the windows that hold an anchor."""
    starts: set[int] = set()
    for a in anchors:
        k = a // STRIDE
        starts.update(range(max(0, -(-(a - LENGTH + 1) // STRIDE)), k + 1))
    return sorted(k * STRIDE for k in starts if k * STRIDE < n)


def find_spans(texts: list[str], tagger: Tagger, all_windows: bool = False) -> list[tuple[list[Span], list[Span]]]:
    """(base spans, added spans) of each text; the windows of all texts are scored together, WINDOWS at a time.

    Without ``all_windows`` those that ``decode`` leaves empty aren't scored; the result is the same.
    """
    base, jobs = [], []
    for i, text in enumerate(texts):
        anchors = [m.start() for m in _ANCHOR.finditer(text)]
        base.append(base_spans(text) if anchors else [])
        jobs += [(i, s) for s in (range(0, len(text), STRIDE) if all_windows else window_starts(anchors, len(text)))]
    merged: dict[tuple[int, int], list[list[int]]] = {}
    for lo in range(0, len(jobs), WINDOWS):
        part = jobs[lo : lo + WINDOWS]
        classes = np.full((LENGTH, len(part)), 27 + _PUNCT.index("\n"), np.int64)
        for j, (i, s) in enumerate(part):
            c = char_classes(texts[i][s : s + LENGTH])
            classes[: len(c), j] = c
        tags = tagger.decode(classes)
        for j in np.flatnonzero(tags.any(axis=0)).tolist():
            i, s = part[j]
            column, t, end = tags[:, j].tolist(), 0, min(LENGTH, len(texts[i]) - s)
            while t < end:
                if not column[t]:
                    t += 1
                    continue
                kind, a = (column[t] - 1) // 2, t
                t += 1
                while t < end and column[t] == 2 + 2 * kind:
                    t += 1
                merged.setdefault((i, kind), []).append([a + s, t + s])
    added: list[list[Span]] = [[] for _ in texts]
    for (i, kind), spans in merged.items():
        spans.sort()
        whole = [spans[0]]
        for a, b in spans[1:]:
            if a < whole[-1][1]:
                whole[-1][1] = max(whole[-1][1], b)
            else:
                whole.append([a, b])
        text = texts[i]
        for a, b in whole:
            while b > a and text[b - 1] in " \n.,":
                b -= 1
            while b > a and text[a] in " \n.,":
                a += 1
            edge = (a and text[a - 1].isalnum()) or (b < len(text) and text[b].isalnum())
            if not edge and _plausible(kind, text[a:b]):
                added[i].append((kind, a, b))
    for i, spans in enumerate(added):
        taken = [(a, b) for _, a, b in base[i]]
        kept: list[Span] = []
        for kind, a, b in sorted(spans, key=lambda x: (x[1] - x[2], x)):
            if all(b <= x or a >= y for x, y in taken):
                taken.append((a, b))
                kept.append((kind, a, b))
        added[i] = kept
    return list(zip(base, added, strict=True))


def written(spans: list[Span]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for k, a, b in sorted(spans))


_COUNTS = [f"n_{k}" for k in KINDS]


def find_personal_data(docs: DataFrame) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone: the patterns' counts; base_sha256; spans: all; n_added). A map, no shuffle."""
    tagger = docs.sparkSession.sparkContext.broadcast(train_tagger())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = find_spans(strings(batch, TEXT), tagger.value)
            counts = [pa.array([sum(s[0] == k for s in b) for b, _ in found], pa.int64()) for k in range(len(KINDS))]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *counts, pa.array([hashlib.sha256(written(b).encode()).hexdigest() for b, _ in found], pa.string()), pa.array([written(b + a) for b, a in found], pa.string()), pa.array([len(a) for _, a in found], pa.int64())],
                names=[ID, *_COUNTS, "base_sha256", "spans", "n_added"],
            )

    return arrow_map(docs.select(ID, TEXT), run, f"{ID} {docs.schema[ID].dataType.simpleString()}, {', '.join(f'{c} long' for c in _COUNTS)}, base_sha256 string, spans string, n_added long")


def redact(texts: list[str], tagger: Tagger) -> list[str]:
    """Texts with every span replaced by its kind in brackets, again until the patterns find no more."""
    out = list(texts)
    todo = list(range(len(texts)))
    while todo:
        again = []
        for i, (base, added) in zip(todo, find_spans([out[i] for i in todo], tagger), strict=True):
            if not base and not added:
                continue
            text, parts, at = out[i], [], 0
            for kind, a, b in sorted(base + added, key=lambda s: (s[1], -s[2])):
                if b <= at:
                    continue
                parts += [text[at : max(a, at)], f"[{KINDS[kind].upper()}]"]
                at = b
            out[i] = "".join(parts) + text[at:]
            again.append(i)
        todo = again
    return out


def redact_personal_data(docs: DataFrame) -> DataFrame:
    """``docs``, all columns, with personal data in the text replaced; null texts stay null; n_chars, if there, follows the text."""
    tagger = docs.sparkSession.sparkContext.broadcast(train_tagger())
    names = docs.columns
    text_at, count_at = names.index(TEXT), names.index("n_chars") if "n_chars" in names else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            old = batch.column(text_at).to_pylist()
            new = redact([x or "" for x in old], tagger.value)
            cols = list(batch.columns)
            cols[text_at] = pa.array([None if x is None else y for x, y in zip(old, new, strict=True)], pa.string())
            if count_at is not None:
                counts = batch.column(count_at).to_pylist()
                cols[count_at] = pa.array([c if x is None or x == y else len(y) for c, x, y in zip(counts, old, new, strict=True)], cols[count_at].type)
            yield pa.RecordBatch.from_arrays(cols, names=names)

    return arrow_map(docs, run, docs.schema)
