import struct
import zlib
from collections import defaultdict

import pytest

from rowsketch.llm import packing
from rowsketch.llm.queries import tokenizer_path


def ids_of(text):
    from tokenizers import Tokenizer

    if not hasattr(ids_of, "t"):
        ids_of.t = Tokenizer.from_file(tokenizer_path())
    return ids_of.t.encode(text or "", add_special_tokens=False).ids + [2]


def check(pieces, texts, window=4096):
    """Every id of every text lies in exactly one piece, and sequences have no gap."""
    by_sequence = defaultdict(list)
    left = defaultdict(list)
    for t in texts:
        ids = ids_of(t)
        left[len(ids)].append(ids)
    spans = defaultdict(list)
    for p in pieces:
        by_sequence[p["sequence_id"]].append((p["offset"], p["length"]))
        spans[p["doc_id"], p["doc_tokens"]].append((p["start"], p["length"], p["ids_crc32"]))
    for s in by_sequence.values():
        at = 0
        for offset, length in sorted(s):
            assert offset == at and length > 0
            at += length
        assert at <= window
    return by_sequence, spans


def test_round_trip(documents):
    pieces = packing.pack_documents(documents, tokenizer_path()).collect()
    text = {r["doc_id"]: r["text"] for r in documents.collect()}
    by_sequence, spans = check(pieces, text.values())
    assert {d for d, _ in spans} == set(text)
    for (d, n), parts in spans.items():
        ids = ids_of(text[d])
        assert len(ids) == n
        raw = struct.pack(f"<{n}I", *ids)
        at = 0
        for start, length, crc in sorted(parts):
            assert start == at and crc == zlib.crc32(raw[4 * start : 4 * (start + length)])
            at += length
        assert at == n
    lengths = [sum(x for _, x in s) for s in by_sequence.values()]
    padding = sum(4096 - x for x in lengths if x & (x - 1))
    assert padding < 0.01 * (sum(lengths) + padding)


def test_odd_rows(odd, none):
    pieces = packing.pack_documents(odd, tokenizer_path(), with_ids=True).collect()
    total = defaultdict(int)
    for p in pieces:
        assert len(p["ids"]) == p["length"]
        total[p["doc_id"]] += p["length"]
    for i, t, times in ((2, None, 1), (3, "", 1), (1, "The cat sat on the mat and looked at the dog.", 2), (7, "Ünïcode — ΑΣ ß 日本 text next", 1)):
        assert total[i] == times * len(ids_of(t))
    assert packing.pack_documents(none, tokenizer_path()).count() == 0


@pytest.mark.parametrize("text", ["The, the. THE Don't can't I'M 12,5 a.b, <|endoftext|>x ,", "a\x1cb\x85c　d", "İstanbul ΟΔΟΣ, éá. 'S 's", "!!!, ... ,,,", "tab\tand\r\nline  two"])
def test_encoding_is_exact(text):
    got = packing.encode([text, text + ",", text.lower()], tokenizer_path())
    for b, t in zip(got, [text, text + ",", text.lower()]):
        assert list(struct.unpack(f"<{len(b) // 4}I", b)) == ids_of(t)[:-1]


@pytest.mark.parametrize("text", ["BİLGİ.", "कक़.", "BİLGİ, कक़, Ünï. ΟΔΟΣ. the."])
def test_combining_marks_join_the_stop(text):
    (got,) = packing.encode([text], tokenizer_path())
    assert list(struct.unpack(f"<{len(got) // 4}I", got)) == ids_of(text)[:-1]


def test_best_fit_takes_the_tightest():
    fit = packing.BestFit(10)
    for size in (7, 6, 4, 3):
        fit.add(size, size)
    assert sorted(map(sorted, fit.bins)) == [[3, 7], [4, 6]]
    fit = packing.BestFit(10)
    for size in (8, 5, 2):
        fit.add(size, size)
    assert sorted(map(sorted, fit.bins)) == [[2, 8], [5]]


def test_best_fit_against_plain_search():
    import random

    random.seed(3)
    sizes = sorted((random.randint(1, 64) for _ in range(400)), reverse=True)
    fit = packing.BestFit(64)
    rooms = []
    for s in sizes:
        fit.add(s, s)
        fits = [r for r in rooms if r >= s]
        if fits:
            rooms.remove(min(fits))
            rooms.append(min(fits) - s)
        else:
            rooms.append(64 - s)
    assert sorted(rooms) == sorted(fit.free)


def test_pouring_keeps_every_id():
    pieces = [(k, 0, 2500, bytes(4 * 2500), 2500) for k in range(9)]
    out = packing.pack(pieces)
    assert sum(p[2] for s in out for p in s) == 9 * 2500
    lengths = [sum(p[2] for p in s) for s in out]
    assert sum(4096 - x for x in lengths if x & (x - 1)) <= 0.01 * sum(lengths)
    for k in range(9):
        spans = sorted((p[1], p[2]) for s in out for p in s if p[0] == k)
        at = 0
        for start, length in spans:
            assert start == at
            at += length
        assert at == 2500


def test_odd_strings_encode_as_the_tokenizer_does():
    """Letters that become letter and mark, zero-width characters and every Unicode blank, before and after marks."""
    import random

    from tokenizers import Tokenizer

    path = tokenizer_path()
    plain = Tokenizer.from_file(path)
    blanks = [chr(c) for c in (9, 10, 11, 12, 13, 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)]
    odd = [*"İıſßΣςǅK", "̇", "́", "ͅ", "​", "‍", "﻿", "क़", "क़", "é", "é", "한", "日", "🙂", "ﬁ", "①", "½", "_", "-", "'", "\x00", "\x1c"]
    common = list("abcXYZ019.,.,.,;!?") + ["the", "İ.", "BİLGİ,", "é.", "क़."]
    rng = random.Random(11)
    texts = ["".join(rng.choice(rng.choice((odd, common, common, blanks))) for _ in range(rng.randint(1, 14))) for _ in range(10_000)]
    got = packing.encode(texts, path)
    for text, ids in zip(texts, got):
        assert list(memoryview(ids).cast("I")) == plain.encode(text, add_special_tokens=False).ids, ascii(text)
