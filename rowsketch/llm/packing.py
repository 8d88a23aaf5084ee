"""Best-fit-decreasing packing of token ids into fixed windows.

A document's ids end with one end id.  Documents longer than a window are cut
into full windows first; what remains is packed best-fit decreasing: a segment
tree over remaining capacities finds the tightest open window.  Where windows
of a batch still hold more than ``max_padding`` free room, the emptiest are
dissolved and poured into the free room of the others (a cut where needed), so
small partitions pack as tightly as large ones; the last one is then cut into
power-of-two sequences, which need no padding.

Packing needs no shuffle: each partition packs what it holds, in batches of
bounded size, and sequence ids carry the partition.  A rerun of a lost task
gives the same pieces.  Null and empty texts are a document of the end id
alone; repeated rows are packed each on their own; an empty table gives no
pieces; other columns are not read.
"""

from __future__ import annotations

import gc
import json
import os
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowsketch.llm.common import release, text_or_empty

WINDOW = 4096
END_ID = 2
#: Open pieces packed together, and their ids; bound a task's memory.
BATCH_PIECES = 100_000
BATCH_IDS = 8_000_000
#: Sequences handed on at once.
EMIT_SEQUENCES = 256
#: Cached token strings of a Python worker.
CACHE_ENTRIES = 200_000
#: Text handled between two looks at the cache.
TEXT_STEP = 4_000_000
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


class BestFit:
    """Open windows by remaining capacity, under a segment tree of occupied leaves."""

    def __init__(self, window: int = WINDOW):
        self.window = window
        self.leaves = 1 << (window + 1).bit_length()
        self.tree = [0] * (2 * self.leaves)
        self.open: list[list[int]] = [[] for _ in range(window + 1)]
        self.bins: list[list] = []
        self.free: list[int] = []

    def _mark(self, room: int, change: int) -> None:
        i = room + self.leaves
        while i:
            self.tree[i] += change
            i >>= 1

    def _tightest(self, size: int) -> int:
        """The least occupied capacity of at least ``size``; -1 if none."""
        tree, i = self.tree, size + self.leaves
        if tree[i]:
            return size
        while i > 1:
            if not i & 1 and tree[i + 1]:
                i += 1
                break
            i >>= 1
        else:
            return -1
        while i < self.leaves:
            i <<= 1
            if not tree[i]:
                i += 1
        return i - self.leaves

    def add(self, size: int, piece) -> None:
        room = self._tightest(size)
        if room < 0:
            b = len(self.bins)
            self.bins.append([])
            self.free.append(self.window)
            room = self.window
        else:
            b = self.open[room].pop()
            self._mark(room, -1)
        self.bins[b].append(piece)
        self.free[b] = room - size
        if room > size:
            self.open[room - size].append(b)
            self._mark(room - size, 1)


def _pour(bins: list[list], free: list[int], window: int, max_padding: float) -> list[list]:
    """Dissolves the emptiest windows while more than ``max_padding`` of all room is free."""
    order = sorted(range(len(bins)), key=lambda b: free[b])  # fullest first
    total = sum(free)
    loose: list = []
    while order and total > max_padding * window * len(order):
        b = order[-1]
        fits = total - free[b] >= window - free[b]
        if not fits and len(order) > 1 and total <= max_padding * window * (len(order) + 1):
            break
        order.pop()
        loose += bins[b]
        total -= window
        if not fits:
            break
    out = [list(bins[b]) for b in order]
    room = [free[b] for b in order]
    k = 0
    pending = loose[::-1]  # pieces: (doc_id, start, length, ids, doc_tokens)
    while pending and k < len(out):
        if not room[k]:
            k += 1
            continue
        doc, start, length, ids, n = pending.pop()
        take = min(length, room[k])
        out[k].append((doc, start, take, ids[: 4 * take], n))
        room[k] -= take
        if take < length:
            pending.append((doc, start + take, length - take, ids[4 * take :], n))
    left = sum(p[2] for p in pending)
    while left:  # one window's worth at most: its binary digits are sequences of their own
        size = 1 << (left.bit_length() - 1)
        size = min(size, window)
        seq, need = [], size
        while need:
            doc, start, length, ids, n = pending.pop()
            take = min(length, need)
            seq.append((doc, start, take, ids[: 4 * take], n))
            need -= take
            if take < length:
                pending.append((doc, start + take, length - take, ids[4 * take :], n))
        out.append(seq)
        left -= size
    return out


def pack(pieces: list, window: int = WINDOW, max_padding: float = 0.005) -> list[list]:
    """Sequences of (doc_id, start, length, ids, doc_tokens) pieces, each piece at most a window long."""
    fit = BestFit(window)
    for p in sorted(pieces, key=lambda p: (-p[2], p[0] is None, p[0] or 0, p[1])):
        fit.add(p[2], p)
    return _pour(fit.bins, fit.free, window, max_padding)


#: How the known tokenizer prepares a text, and cuts it into pieces that its model encodes one by one.
NORMALISERS = ["NFC", "Replace", "Lowercase"]
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"

#: Letters that normal form and lower case leave letters, and the punctuation after them: pieces apart, whatever stands beside them.
_LETTERS = "A-Za-zÀ-ÖØ-öø-ÿ"
_CUT = re.compile(rf"([{_LETTERS}]+)([!-&(-/:-@\[-`{{-~]*)").fullmatch
#: Texts of such letters, blanks and any other ASCII.
_PLAIN = re.compile(r"[\n -~À-ÖØ-öø-ÿ]*").fullmatch


class _Ids(dict):
    """Ids, as bytes, of strings without blanks; each is encoded when it is first asked for.

    A run of letters and the marks after it are pieces apart, and the tokenizer
    lower-cases, so "The," costs no more than "the" and ",", and pieces go
    straight to the tokenizer's model.  Letters beyond Latin-1 may become a
    letter and a combining mark, which joins the stop, and an apostrophe may
    begin a piece with letters; such strings are left to the whole tokenizer.
    """

    def __init__(self, tokenizer):
        from tokenizers.pre_tokenizers import ByteLevel

        super().__init__({"": b""})
        self.tokenizer, self.model = tokenizer, tokenizer.model
        level = ByteLevel(add_prefix_space=False, use_regex=False)
        self.spelt = {c: level.pre_tokenize_str(chr(c))[0][0] for c in range(0xC0, 0x100)}

    def __missing__(self, s: str) -> bytes:
        m = _CUT(s)
        if m is None:
            got = array("I", self.tokenizer.encode(s, add_special_tokens=False).ids).tobytes()
        else:
            word, mark = m.groups()
            got = self.piece(word.lower()) + (self.piece(mark) if mark else b"")
        self[s] = got
        return got

    def piece(self, s: str) -> bytes:
        got = self.get(s)
        if got is None:
            spelt = s if s.isascii() else s.translate(self.spelt)
            got = self[s] = array("I", [t.id for t in self.model.tokenize(spelt)]).tobytes()
        return got

    def keep(self, strings: set[str]) -> None:
        """Forgets all but these."""
        kept = {s: self[s] for s in strings if s in self}
        self.clear()
        self.update(kept)
        self[""] = b""


_ENCODERS: dict[str, tuple] = {}


def _encoder(path: str):
    """(tokenizer, ids) of this worker; the ids are None for a tokenizer that prepares its texts in another way."""
    if path not in _ENCODERS:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            told = json.load(f)
        normal, pieces = told.get("normalizer") or {}, told.get("pre_tokenizer") or {}
        parts = pieces.get("pretokenizers") or [{}]
        known = [n["type"] for n in normal.get("normalizers", [])] == NORMALISERS and parts[0].get("pattern") == {"Regex": PIECES} and [x.get("type") for x in parts[1:]] == ["ByteLevel"]
        t = Tokenizer.from_file(path)
        _ENCODERS[path] = (t, _Ids(t) if known and told["model"]["type"] == "BPE" else None)
    return _ENCODERS[path]


def encode(texts: list[str], path: str) -> list[bytes]:
    """Each text's ids as little-endian unsigned 32-bit integers.

    The known tokenizer never joins across white space, so texts are cut at
    blanks and line feeds and each distinct string is encoded once a worker;
    any other white space stays inside its string and is left to the
    tokenizer.  Other tokenizers encode whole texts.
    """
    tokenizer, ids = _encoder(path)
    if ids is None:
        return [array("I", e.ids).tobytes() for e in tokenizer.encode_batch(texts, add_special_tokens=False)]
    out: list[bytes] = []
    at = 0
    gc.disable()  # strings and lists only, none of them in cycles
    while at < len(texts):
        end, size = at, 0
        while end < len(texts) and (end == at or size < TEXT_STEP):
            size += len(texts[end])
            end += 1
        # plain texts are lower-cased at once, so that fewer strings are told apart
        parts = [(t.lower() if _PLAIN(t) else t).replace("\n", " ").split(" ") for t in texts[at:end]]
        if len(ids) > CACHE_ENTRIES:
            ids.keep(set().union(*parts))
        get = ids.__getitem__
        out += [b"".join(map(get, p)) for p in parts]
        at = end
    gc.enable()
    return out


def pack_documents(docs: DataFrame, tokenizer_path: str, *, window: int = WINDOW, end_id: int = END_ID, max_padding: float = 0.005, with_ids: bool = False, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Pieces of packed sequences; ``with_ids`` adds the pieces' ids as ``ids array<int>``."""
    end = end_id.to_bytes(4, "little")
    schema = SCHEMA + (", ids array<int>" if with_ids else "")
    kinds = [pa.int64()] * 7
    names = SCHEMA.replace(" long", "").split(", ") + (["ids"] if with_ids else [])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base = TaskContext.get().partitionId() << 32
        made = 0

        def emit(sequences: list) -> Iterator[pa.RecordBatch]:
            nonlocal made
            for at in range(0, len(sequences), EMIT_SEQUENCES):
                rows, ids = [], []
                for seq in sequences[at : at + EMIT_SEQUENCES]:
                    offset = 0
                    for doc, start, length, b, n in seq:
                        rows.append((doc, start, length, zlib.crc32(b), n, base + made, offset))
                        ids.append(b)
                        offset += length
                    made += 1
                cols = [pa.array(c, k) for c, k in zip(zip(*rows), kinds)]
                if with_ids:
                    ends = np.cumsum([0, *(r[2] for r in rows)], dtype=np.int32)
                    cols.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(ids), "<i4"))))
                yield pa.RecordBatch.from_arrays(cols, names)

        waiting: list = []
        held = 0
        full: list = []
        for rb in batches:
            for doc, b in zip(rb.column(0).to_pylist(), encode_arrow(rb.column(1), tokenizer_path)):
                b += end
                n = len(b) // 4
                whole = n // window
                for k in range(whole):
                    full.append([(doc, k * window, window, b[4 * k * window : 4 * (k + 1) * window], n)])
                rest = n - whole * window
                if rest:
                    waiting.append((doc, whole * window, rest, b[4 * whole * window :], n))
                    held += rest
                if len(full) >= EMIT_SEQUENCES:
                    yield from emit(full)
                    full = []
                if len(waiting) >= BATCH_PIECES or held >= BATCH_IDS:
                    yield from emit(pack(waiting, window, max_padding))
                    waiting, held = [], 0
                    release()
        yield from emit(full)
        yield from emit(pack(waiting, window, max_padding))
        full, waiting = [], []
        release()

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), text_or_empty(text).alias("text")).mapInArrow(run, schema)


def encode_arrow(column: pa.Array, path: str) -> Iterator[bytes]:
    """Encodes a column a few megabytes at a time."""
    step, at, n = 256, 0, len(column)
    while at < n:
        yield from encode(column.slice(at, step).to_pylist(), path)
        at += step
