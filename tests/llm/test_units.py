"""Operators' cores against brute force, without Spark."""

import random
import re
import time
import tracemalloc
import zlib

import numpy as np
import pyarrow as pa
import pytest

from graphpart.llm import ann, bpe, components, jaccard, langid, media, packing, pii, quality, tokens
from graphpart.llm.queries import tokenizer_path

ODD = [*"abcXYZ  \n\t.,'!?09²½ªéß<|>_-", "<|endoftext|>", "<|startoftext|>", "\x1c", "\x85", "\xa0", " ", "ﬁ", "Σ", "İ", "日本", "😀", "́", "'re", "'LL", " the", "  ", "\r\n"]


def odd_texts(n, seed=1, most=50):
    rng = random.Random(seed)
    return ["", *("".join(rng.choices(ODD, k=rng.randint(0, most))) for _ in range(n))]


def test_word_ids_equal_the_library():
    v = tokens.word_vocabulary(tokenizer_path("word_bpe_49k.json"))
    for text in odd_texts(1500):
        assert v.ids(v.numbers(text)).tolist() == v.library.encode(text, add_special_tokens=False).ids, repr(text)


def test_every_prefix_count_equals_the_library():
    c = tokens.prefix_counts(tokenizer_path("word_bpe_49k.json"))
    more = ["e\u0301te\u0301 \u1112\u1161\u11ab\uae00", "don'tll 'll x'lly''re", "\u65e5\u672c\u8a9e\u306e\u6587\u7ae0 \u0130stanbul \u03a3\u03af\u03c3\u03c5\u03c6\u03bf\u03c2", "a\u0301\u0323b\u0323\u0301 12\u00b2a1a1", "\u0915\u094d\u0937\u093f \u0e20\u0e32\u0e29\u0e32\u0e44\u0e17\u0e22"]
    for text in (t for t in [*odd_texts(150, 2, 25), *more] if "<|" not in t):
        table = tokens.PrefixTable(c, text)
        counts = [len(c.vocabulary.library.encode(text[:i], add_special_tokens=False).ids) for i in range(len(text) + 1)]
        assert [table.count(i) for i in range(len(text) + 1)] == counts, repr(text)
        for budget in range(0, counts[-1] + 1, 3):
            cut = table.truncate(budget)
            assert counts[cut] <= budget


@pytest.mark.parametrize("unit,times", [("1a", 500_000), ("qzxvbaon", 125_000), ("\u65e5\u672c\u8a9e\u306e", 85_000), ("Zm9vYmFy+/", 100_000)])
def test_a_long_unbroken_chunk_takes_linear_time(unit, times):
    c = tokens.prefix_counts(tokenizer_path("word_bpe_49k.json"))
    text = unit * times
    began = time.time()
    table = tokens.PrefixTable(c, text)
    cut = table.truncate(2048)
    assert time.time() - began < 30  # some seconds; far more if quadratic
    encode = lambda t: len(c.vocabulary.library.encode(t, add_special_tokens=False).ids)
    assert table.count() == encode(text)
    assert encode(text[:cut]) <= 2048
    for i in (1, 7, 1000, 5001):
        assert table.count(i) == encode(text[:i])


def test_byte_ids_and_round_trip():
    v = bpe.byte_vocabulary(tokenizer_path("byte_bpe_50k.json"))
    for text in [*odd_texts(1200), "\n".join(odd_texts(200, 5)) * 3]:
        ids = v.library.encode(text, add_special_tokens=False).ids
        assert np.frombuffer(v.encode(text), "<u4").tolist() == ids, repr(text)
        assert v.decode(np.array(ids, np.int64)).decode("utf-8", "replace") == v.library.decode(ids, skip_special_tokens=False)


def test_cuts_follow_the_content():
    rng = random.Random(3)
    shared = "".join(rng.choices("abcdefgh ", k=70_000))
    a, b = bpe.content_cuts("x" * 5 + shared), bpe.content_cuts("yy" * 50 + shared)
    assert {c - 5 for c in a if c > 40} == {c - 100 for c in b if c > 135}


@pytest.mark.parametrize("h,w", [(1, 64), (7, 64), (33, 5), (16, 16)])
def test_images_round_trip_and_resize(h, w):
    img = np.random.default_rng(h).integers(0, 256, (h, w)).astype(np.uint8)
    assert (media.decode(media.encode_pgm(img)) == img).all()
    assert (media.decode(media.encode_bmp(img)) == img).all()
    rgb = np.stack([img, img[::-1], img], axis=2)
    assert (media.decode(media.encode_ppm(rgb)) == rgb).all()
    fine = np.kron(img, np.ones((8, 9)))  # exact means by brute force on a common grid
    want = fine.reshape(8, h, 9, w).mean(axis=(1, 3)) if fine.shape == (8 * h, 9 * w) else None
    assert np.allclose(media.resize_area(img, 8, 9), want)
    assert np.load(__import__("io").BytesIO(media.npy_tile(img))).shape == (16, 16)


def test_plain_netpbm():
    assert media.decode(b"P2 # grey\n2 1\n255\n0 7\n").tolist() == [[0, 7]]
    assert media.decode(b"P1\n2 1\n1 0\n").tolist() == [[0, 255]]
    assert media.decode(b"P4\n3 1\n\xa0").tolist() == [[0, 255, 0]]


PATTERNS = (
    (0, r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda s: True),
    (1, r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", pii._ip_ok),
    (2, r"[0-9]([\x20-]?[0-9])+", pii._card_ok),
    (3, r"\+[0-9][\x20().0-9-]+[0-9]", pii._phone_ok),
)


def test_base_spans_equal_the_patterns():
    rng = random.Random(2)
    bits = [*"ab1234567890@.+-() _%", "192.168.1.1", "4663622617512349", "+1 (968) 555-9369", "a@b.co", "555-666-7777"]
    for _ in range(4000):
        text = "".join(rng.choices(bits, k=rng.randint(0, 25)))
        want = [(k, m.start(), m.end()) for k, p, ok in PATTERNS for m in re.finditer(p, text) if ok(m[0])]
        assert pii.base_spans(text) == want


def test_tagger_gradient():
    rng = np.random.default_rng(0)
    tagger = pii.Tagger()
    classes, tags = pii.labelled_windows(rng, 2)
    classes, tags = classes[:6], tags[:6]
    _, grad = tagger.loss_and_gradient(classes, tags)
    for name in ("O", "T", "WF", "WB", "S"):
        at = tuple(rng.integers(0, n) for n in tagger.p[name].shape)
        was, eps = tagger.p[name][at], 1e-5
        tagger.p[name][at] = was + eps
        up = tagger.loss_and_gradient(classes, tags)[0]
        tagger.p[name][at] = was - eps
        down = tagger.loss_and_gradient(classes, tags)[0]
        tagger.p[name][at] = was
        assert grad[name][at] == pytest.approx((up - down) / (2 * eps), abs=1e-5)


def test_tagger_adds_and_redacts():
    tagger = pii.train_tagger()
    assert pii.redact(["call (968) 555-9369 now"], tagger) == ["call [PHONE] now"]
    assert pii.redact(["on 2024-01-02 at 12:30 5 items", ""], tagger) == ["on 2024-01-02 at 12:30 5 items", ""]
    assert not pii.base_spans(pii.redact(["+1 4663622617512349 a@b.co 1.2.3.4"], tagger)[0])


def test_shingle_sets_and_tiles():
    rng = random.Random(4)
    texts = []
    for _ in range(30):
        words = [f"w{rng.randint(0, 400)}" for _ in range(rng.randint(5, 60))]
        for _ in range(3):
            w = list(words)
            for _ in range(rng.randint(0, 3)):
                w[rng.randrange(len(w))] = "new" + str(rng.random())
            texts.append(" ".join(w))
    sets = [jaccard.shingle_set(t) for t in texts]
    plain = [{tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)} for t in texts]
    assert [s.size for s in sets] == [len(p) for p in plain]
    want, got = components.UnionFind(), components.UnionFind()
    for i in range(len(texts)):
        for j in range(i):
            if 100 * len(plain[i] & plain[j]) >= 75 * len(plain[i] | plain[j]):
                want.union(i, j)
    for a, b in jaccard.tile_links(sets, list(range(len(sets))), [0] * len(sets)):
        got.union(a, b)
    assert [want.find(i) for i in range(len(texts))] == [got.find(i) for i in range(len(texts))]


def test_long_prefixes_share_enough():
    rng = np.random.default_rng(1)
    for _ in range(300):
        n = int(rng.integers(1, 80))
        pool = np.unique(rng.integers(0, 1 << 60, 200).astype(np.uint64))
        a = np.sort(rng.choice(pool, n, replace=False))
        b = np.sort(np.unique(np.r_[rng.choice(a, rng.integers(1, n + 1), replace=False), rng.choice(pool, rng.integers(0, 20))]))
        shared = np.intersect1d(a, b).size
        if 4 * shared >= 3 * (a.size + b.size - shared):
            met = np.intersect1d(a[: jaccard.long_prefix(a.size)], b[: jaccard.long_prefix(b.size)]).size
            for x in (a, b):
                assert met >= jaccard.least_shared(x.size) // 8 + 1


def test_new_words_of_a_batch_are_encoded_in_one_call(monkeypatch):
    v = tokens.WordVocabulary(tokenizer_path("word_bpe_49k.json"))
    one_by_one, calls, core = [], [], v.spaced

    class Counted:
        def encode_to_tiktoken_buffer(self, text, special):
            calls.append(text)
            return core.encode_to_tiktoken_buffer(text, special)

    monkeypatch.setattr(v, "piece_ids", one_by_one.append)
    monkeypatch.setattr(v, "spaced", Counted())
    texts = ["A qua, it's D\u00c9J\u00c0 vu\xa0!", None, "", "  \n ", "qua qua 'tis 12x,, ", "y" * 700 + " " + "a." * 300, *(f"w{i} Zor{i}." for i in range(300))]
    batch = pa.RecordBatch.from_arrays([pa.array(texts, pa.string())], names=["text"])
    got, ids, sizes = packing._encoded(batch, v)
    assert got == [t or "" for t in texts] and not one_by_one and len(calls) == 1
    assert packing._encoded(batch, v)[1].tolist() == ids.tolist() and "zor" in calls[0] and "zor" not in calls[1]  # known but for the long ones
    want = [v.library.encode(t or "", add_special_tokens=False).ids + [2] for t in texts]
    assert sizes.tolist() == [len(x) for x in want] and ids.tolist() == [i for x in want for i in x]


def test_batches_have_the_ids_of_single_texts(monkeypatch):
    rng = random.Random(5)
    v = tokens.WordVocabulary(tokenizer_path("word_bpe_49k.json"))
    parts = [*map(chr, range(256)), "\u00c9t", "\U0001f600", "\u017f", "\u0130", "<|endoftext|>", "'ll", " one ", " two,", "\u3000"]
    texts = ["".join(rng.choices(parts, k=rng.randint(0, 40))) for _ in range(400)]
    texts += ["".join(rng.choices("ab c,'1\n", k=rng.randint(0, 60))) for _ in range(400)]
    for together in (1, 50, 1 << 22):
        monkeypatch.setattr(tokens, "TOGETHER", together)
        v.reset()
        _, ids, sizes = packing._encoded(pa.RecordBatch.from_arrays([pa.array(texts)], names=["text"]), v)
        want = [v.library.encode(t, add_special_tokens=False).ids + [2] for t in texts]
        assert sizes.tolist() == [len(x) for x in want] and ids.tolist() == [i for x in want for i in x]
    ends = v.ends
    doc, slot = packing.word_slots(ids, sizes, ends)  # against one word at a time
    at, seen = 0, []
    for d, n in enumerate(sizes.tolist()):
        some, word = ids[at : at + n - 1].tolist(), []
        at += n
        for k, i in enumerate(some):
            word.append(i)
            if ends[i] or k == len(some) - 1:
                x = sum(int(packing._OF_ID[t]) * int(packing._OF_PLACE[min(p, 255)]) for p, t in enumerate(word)) & (1 << 64) - 1
                seen.append((d, int(packing._mixed(np.array([x], np.uint64))[0]) >> 44))
                word = []
    assert packing.SLOTS == 1 << 20 and list(zip(doc.tolist(), slot.tolist(), strict=True)) == seen


def test_packing_covers_every_id_once():
    rng = np.random.default_rng(2)
    lengths = rng.integers(1, 9000, 60)
    terms = [rng.integers(0, 300, rng.integers(0, 50)) for _ in range(60)]
    rows = packing.pack_shard(lengths, terms)
    seen = [[] for _ in lengths]
    for pieces in rows:
        total = sum(p[2] for p in pieces)
        assert total == 4096 or total & (total - 1) == 0
        for d, s, n in pieces:
            seen[d].append((s, n))
    for d, n in enumerate(lengths):
        at = 0
        for s, m in sorted(seen[d]):
            assert s == at and m > 0
            at += m
        assert at == n
    assert packing.pack_shard(np.zeros(0, np.int64), []) == []


def test_neighbours_come_first():
    index = packing.Bm25Index([np.array([1, 2, 3, 9]), np.array([7, 8]), np.array([1, 2, 3]), np.array([3, 7])])
    assert index.scores(0).argsort()[::-1][:2].tolist() in ([0, 2], [2, 0])


def test_quality_learns_shapes():
    rng = random.Random(1)
    word = lambda: "".join(rng.choices("abcdefg", k=rng.randint(2, 8)))
    good = [" ".join(word() for _ in range(40)) for _ in range(150)]
    bad = [" ".join(word().upper() + "!!" for _ in range(40)) for _ in range(150)]
    w, b = quality.train([(t, 1) for t in good[:100]] + [(t, 0) for t in bad[:100]])
    s = quality.scores(good[100:] + bad[100:] + [""], w, b)
    assert s[:50].min() > 0.5 > s[50:100].max()
    assert 0 <= s[-1] <= 1


def test_quality_trains_on_rows_held_small():
    rng = np.random.default_rng(5)
    pairs = [(" ".join(map(str, rng.integers(0, 2000, 3000).tolist())), i % 2) for i in range(150)]
    terms = sum(np.unique(quality.TermHasher().slots(t)).size for t, _ in pairs)

    def peak(some):
        tracemalloc.start()
        try:
            quality.train(some, epochs=1)
            return tracemalloc.get_traced_memory()[1]
        finally:
            tracemalloc.stop()

    fixed = peak(pairs[:10])
    assert (peak(pairs) - fixed) / (terms * 140 / 150) < 8  # bytes of a term


def test_language_model():
    pairs = [("the quick brown fox and the dog", "en"), ("der schnelle braune fuchs und der hund", "de")] * 20
    langs, table, prior = langid.train(pairs)
    pred, score = langid.predict(["the dog and the fox", "und der hund", "12 !?", ""], langs, table, prior)
    assert pred == ["en", "de", "und", "und"] and score[2:] == [0.0, 0.0] and all(0 <= x <= 1 for x in score)
    assert langid.predict(["x"], *langid.train([]))[0] == ["und"]


def test_long_texts_have_the_grams_of_the_whole(monkeypatch):
    rng = np.random.default_rng(9)
    model = langid.train([("the quick brown fox", "en"), ("der schnelle fuchs", "de")] * 5)
    texts = ["".join(chr(97 + c) for c in rng.integers(0, 26, n)) for n in (62, 63, 64, 65, 190, 191, 192, 193, 1000)]
    want = langid.predict(texts, *model)
    monkeypatch.setattr(langid, "SLICE_CHARS", 64)
    assert langid.predict(texts, *model) == want


def test_scores_are_sparse_dot_products():
    rng = np.random.default_rng(10)
    w = rng.normal(size=1 << quality.BITS)
    texts = ["One two two 3 four!", "", "x", "a b c d e f g " * 300]
    for text, got in zip(texts, quality.scores(texts, w, 0.25), strict=True):
        assert abs(got - quality_by_hand(text, w, 0.25)) < 1e-9


def quality_by_hand(text, w, b):
    words = text.split()
    word, shape = [zlib.crc32(x.encode()) for x in words], [zlib.crc32(quality.shape_of(x).encode(), 7) >> 1 for x in words]
    terms = [x * 3 for x in word] + [x * 5 + 1 for x in shape]
    terms += [x * 7919 + y * 104729 + 2 for x, y in zip(word, word[1:])] + [x * 6151 + y * 24593 + 3 for x, y in zip(shape, shape[1:])]
    terms += [4 for x, y in zip(word, word[1:]) if x == y]
    z = b + (quality.GAIN * sum(w[(t * 0x9E3779B97F4A7C15 & (1 << 64) - 1) >> 64 - quality.BITS] for t in terms) / len(terms) if terms else 0.0)
    return 1 / (1 + np.exp(-z))


def test_graph_search_finds_near_lists():
    rng = np.random.default_rng(5)
    c = rng.normal(size=(80, 8))
    g = ann.CentroidGraph(c)
    hits = 0
    for q in rng.normal(size=(40, 8)):
        best = int(((c - q) ** 2).sum(axis=1).argmin())
        hits += best in g.search(q, 1.2).tolist()
    assert hits >= 38


def test_crc_of_ids_is_little_endian():
    assert zlib.crc32(np.array([1, 2], np.uint16).astype("<u4")) == zlib.crc32(b"\x01\0\0\0\x02\0\0\0")


def test_a_seed_is_scored_by_all_its_terms():
    shared, pairs = np.arange(1000, 1010), [np.array([2 * i, 2 * i + 1]) for i in range(30)]
    docs = [np.concatenate([*pairs, shared]), *pairs, *[np.concatenate([shared, [5000 + i]]) for i in range(6)]]
    assert (packing.Bm25Index(docs).scores(0)[-6:] > 0).all()
