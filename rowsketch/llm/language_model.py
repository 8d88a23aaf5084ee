"""Language-model scores from a weighted backoff automaton over word n-grams.

Model.  Words are the runs without white space, A-Z lower-cased; a text ends
with one end token.  The lowest level is the add-half word distribution.  Each
higher level n mixes, for a history h that training has seen,

    p_n(w | h) = (1 - L_n) * c(h w) / c(h) + L_n * p_(n-1)(w | h without its first word)

with L_n the share of n-gram tokens that training saw once, the leave-one-out
estimate of what a history leaves open.  As an automaton: a state is a
seen history, an arc a seen n-gram with its full weight, and the failure arc of
a state leads to the longest shorter history with weight log10 L_n.  A text is
read once from left to right; at each token the machine follows failure arcs
until it finds the word's arc, adds the weights it passes, and moves to the
arc's end.  All texts of a block are read in step; a long one is cut into
stretches, each of which reads the ``order - 1`` tokens before it first: a
state remembers no more than these, so it starts where the stretch before ends.

Scale.  Texts are read in blocks of bounded bytes.  A block sends the sorted
hashes of its n-grams, each once with its count in training texts, to nodes by
hash range, and gets back the totals of what it asked for, so it holds only the
part of the automaton that its texts can reach.  Ranges are cut FAN ways at a
time: a node adds up what FAN blocks ask of one range and asks, in their place,
the nodes of the next, finer ranges, until one node answers for all blocks.
Every step sends a bounded number of messages a block, there are log(blocks)
steps, and a node holds about as much as a block.  Nothing is broadcast or
pruned, no n-gram is dropped, and every table is as large as its share of the
corpus.

Null and empty texts are the end token alone; a null id counts as the empty
string where folds are dealt; repeated rows are scored (and, in training folds,
counted) each; an empty table gives an empty result; other columns are not read.
The texts are scanned twice; where a shuffle lies below them, they are written
to the shared folder first, so that both scans see one order.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowsketch.llm.common import fold_of, text_bytes
from rowsketch.shared import materialise

ORDER = 3
FOLDS = 5
HELD_OUT = 1
#: Text bytes of a block; a longer text is a block of its own.
BLOCK_BYTES = 8_000_000
#: Blocks whose questions a node adds up, and ranges it cuts its own into.
FAN = 256
#: Ranges of the last step for each block that is left.
LAST_RANGES = 8 / 3
#: Tokens that are read in one stretch.
STRETCH = 256
#: Bits of a hash: words are told apart by all 64; longer n-grams travel shorter
#: (10 million million of them still collide in less than one case of a thousand).
WORD_BITS = 64
GRAM_BITS = 54
END = b"\n"
BEGIN = b"\t"
_MIX = np.uint64(0x9E3779B97F4A7C15)
_MIX2 = np.uint64(0xC2B2AE3D27D4EB4F)


def _joined(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """A 64-bit hash of two hashes, order kept."""
    x = (left ^ (left >> np.uint64(29))) * _MIX + right
    x ^= x >> np.uint64(32)
    x *= _MIX2
    return x ^ (x >> np.uint64(29))


def _pack(values: np.ndarray) -> bytes:
    """Unsigned integers as compressed byte planes, in as many bytes as the largest needs."""
    import zstandard

    size = max(1, -(-int(values.max()).bit_length() // 8)) if len(values) else 0
    planes = np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :size].T) if size else np.empty(0, np.uint8)
    return bytes([size]) + zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def _unpack(data: bytes) -> np.ndarray:
    import zstandard

    if not data[0]:
        return np.empty(0, np.uint64)
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data[1:]), np.uint8).reshape(data[0], -1)
    wide = np.zeros((planes.shape[1], 8), np.uint8)
    wide[:, : data[0]] = planes.T
    return wide.view("<u8").reshape(-1)


class Block:
    """The n-grams of some texts: per order the sorted distinct hashes, and where each token's n-gram is among them."""

    def __init__(self, texts: list[bytes], order: int):
        import xxhash

        ids: dict[bytes, int] = {BEGIN: 0, END: 1}
        get = ids.setdefault
        lengths = np.empty(len(texts), np.int64)
        parts = []
        for k, t in enumerate(texts):
            words = t.lower().split()
            lengths[k] = len(words) + 1
            row = np.fromiter((get(w, len(ids)) for w in words), np.int32, len(words))
            parts += [row, np.ones(1, np.int32)]
        token = np.concatenate(parts) if parts else np.empty(0, np.int32)
        self.lengths = lengths
        self.starts = np.cumsum(lengths) - lengths
        word_hash = np.fromiter((xxhash.xxh64_intdigest(w) for w in ids), np.uint64, len(ids))
        first = np.zeros(len(token), bool)
        first[self.starts] = True
        #: For each order: hashes (sorted, distinct), token -> row among them (-1: the text has no such n-gram there), rows one order below of the n-gram without its last and without its first word.
        self.hashes: list[np.ndarray] = []
        self.at: list[np.ndarray] = []
        self.history: list[np.ndarray] = []
        self.suffix: list[np.ndarray] = [np.empty(0, np.int64)]
        used = np.unique(token)
        by_hash = np.argsort(word_hash[used])
        rank = np.zeros(len(ids), np.int64)
        rank[used[by_hash]] = np.arange(len(used))
        self.hashes.append(word_hash[used[by_hash]])
        self.at.append(rank[token])
        self.history.append(np.empty(0, np.int64))
        begin = len(used)  # stands for the begin mark, a history only
        below = np.concatenate([[begin], self.at[0][:-1]]) if len(token) else np.empty(0, np.int64)
        below[first] = begin
        hash_below = np.concatenate([self.hashes[0], word_hash[:1]])
        valid = np.ones(len(token), bool)
        for n in range(2, order + 1):
            if n > 2:
                # the history is the (n-1)-gram that ended at the token before
                prev = np.concatenate([[-1], self.at[n - 2][:-1]]) if len(token) else np.empty(0, np.int64)
                prev[first] = -1
                below, valid = prev, prev >= 0
                hash_below = self.hashes[n - 2]
            wide = np.int64(len(used))
            code = below[valid] * wide + self.at[0][valid]
            distinct, where = np.unique(code, return_inverse=True)
            h = _joined(hash_below[distinct // wide], self.hashes[0][distinct % wide]) >> np.uint64(64 - GRAM_BITS)
            by_hash = np.argsort(h, kind="stable")
            rank = np.empty(len(h), np.int64)
            rank[by_hash] = np.arange(len(h))
            at = np.full(len(token), -1, np.int64)
            at[valid] = rank[where]
            self.hashes.append(h[by_hash])
            self.at.append(at)
            self.history.append((distinct // wide)[by_hash])
            suffix = np.empty(len(h), np.int64)
            suffix[at[valid]] = self.at[n - 2][valid]
            self.suffix.append(suffix)

    def counts(self, train: np.ndarray) -> list[np.ndarray]:
        """Per order, occurrences of each row in the texts marked for training."""
        mark = np.repeat(train, self.lengths)
        return [np.bincount(at[mark & (at >= 0)], minlength=len(h)).astype(np.uint32) for at, h in zip(self.at, self.hashes)]


def fan_outs(members: int, fan: int = FAN) -> list[int]:
    """Into how many ranges each step cuts, so that ``members`` blocks are one after the last."""
    out = []
    while members > fan:
        out.append(fan)
        members = -(-members // fan)
    return [*out, max(8, math.ceil(LAST_RANGES * members))]


def range_cuts(hashes: np.ndarray, path: int, parts: int, ranges: int, bits: int) -> np.ndarray:
    """Where the ``parts`` ranges below range ``path`` begin in its sorted hashes; ``ranges`` there are in all."""
    edges = ((path * parts + np.arange(parts, dtype=np.float64)) / ranges * 2.0**bits).astype(np.uint64)
    cuts = np.searchsorted(hashes, edges)
    cuts[0] = 0
    return np.append(cuts, len(hashes))


def merged(asked: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """(hashes, counts) of several askers as one: distinct hashes, their sums, and where each asker's hashes are among them."""
    hashes = np.concatenate([h for h, _ in asked])
    counts = np.concatenate([c for _, c in asked])
    order = np.argsort(hashes, kind="stable")
    ordered = hashes[order]
    first = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]])) if len(ordered) else np.empty(0, np.int64)
    sums = np.add.reduceat(counts[order], first) if len(first) else np.empty(0, np.uint64)
    back = np.empty(len(hashes), np.int64)
    back[order] = np.repeat(np.arange(len(first)), np.diff(np.concatenate([first, [len(hashes)]])))
    return ordered[first], sums, np.split(back, np.cumsum([len(h) for h, _ in asked])[:-1])


class Automaton:
    """States and arcs that one block's texts can reach, with weights from the whole corpus.

    State 0 has no history; then come the block's words and the begin mark as
    histories of one word, its bigrams as those of two, and so on, each level
    numbered as the block numbers its n-grams.  An arc is an n-gram that
    training has seen: the state of its history, its last word, a weight, and
    the state it leads to.  The block numbers the n-gram that a state's history
    and a token make, so an arc is found by its number.
    """

    def __init__(self, block: Block, totals: list[np.ndarray], stats: np.ndarray, trained_texts: int):
        # stats: per order (tokens, types, types seen once) over all training texts
        tokens, types, _ = stats[0]
        self.block, self.order = block, len(totals)
        self.tokens, self.types = int(tokens), int(types)
        self.known = totals[0] > 0
        self.base = np.log10((totals[0] + 0.5) / (tokens + 0.5 * (types + 1)))
        words = len(totals[0])
        #: First state of each level, by the length of its histories.
        self.first = np.cumsum([0, 1, words + 1, *[len(t) for t in totals[1:]]])[: self.order + 1]
        states = int(self.first[-1]) if self.order > 1 else 1
        self.begin = int(self.first[1]) + words if self.order > 1 and trained_texts else 0
        self.fail = np.zeros(states, np.int64)
        self.fail_weight = np.zeros(states)
        #: For each order, the weight of an n-gram's arc (nan: there is none), and the state that it leads to.
        self.weight: list[np.ndarray] = [self.base]
        self.to: list[np.ndarray] = [np.where(self.known, 1 + np.arange(words), 0) if self.order > 1 else np.zeros(words, np.int64)]
        below = np.append(totals[0], trained_texts)
        p = np.power(10.0, self.base)
        for n in range(2, self.order + 1):
            share = min(max(stats[n - 1][2] / max(stats[n - 1][0], 1), 1e-6), 1.0)
            level = self.first[n - 1]
            self.fail_weight[level : level + len(below)] = math.log10(share)
            if n > 2:
                self.fail[level : level + len(below)] = self.first[n - 2] + block.suffix[n - 2]
            has = totals[n - 1] > 0
            history = np.where(has, below[block.history[n - 1]], 1)
            lower = p[block.suffix[n - 1]]
            p = np.where(has, (1 - share) * totals[n - 1] / history + share * lower, lower)
            self.weight.append(np.where(has, np.log10(p), np.nan))
            shorter = self.to[n - 2][block.suffix[n - 1]]
            self.to.append(np.where(has, self.first[n] + np.arange(len(has)), shorter) if n < self.order else shorter)
            below = totals[n - 1]

    def read(self, stretch: int = STRETCH) -> np.ndarray:
        """log10 probability of each token, from left to right; all stretches of all texts move in step."""
        block = self.block
        warm = self.order - 1
        ends = block.starts + block.lengths
        pieces = -(-block.lengths // stretch)
        text = np.repeat(np.arange(len(ends)), pieces)
        nth = np.arange(len(text)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        start = block.starts[text] + nth * stretch
        end = np.minimum(start + stretch, ends[text])
        at = np.where(nth > 0, np.maximum(start - warm, block.starts[text]), start)
        state = np.where(at == block.starts[text], self.begin, 0)
        out = np.zeros(len(block.at[0]))
        live = np.arange(len(text))
        while len(live):
            token = at[live]
            now, total = state[live], np.zeros(len(live))
            level = np.searchsorted(self.first, now, "right") - 1
            open_ = np.arange(len(live))
            for n in range(self.order, 0, -1):  # who is at a state of n - 1 words takes its arc or fails
                here = open_[level[open_] == n - 1]
                if not len(here):
                    continue
                arc = block.at[n - 1][token[here]]
                weight = np.where(arc >= 0, self.weight[n - 1][arc], np.nan)
                found = ~np.isnan(weight)
                took = here[found]
                total[took] += weight[found]
                now[took] = self.to[n - 1][arc[found]]
                level[took] = -1
                lost = here[~found]
                total[lost] += self.fail_weight[now[lost]]
                now[lost] = self.fail[now[lost]]
                level[lost] -= 1
            counts = token >= start[live]
            out[token[counts]] = total[counts]
            state[live] = now
            at[live] += 1
            live = live[at[live] < end[live]]
        return out


def _blocks(batches: Iterator[pa.RecordBatch], block_bytes: int) -> Iterator[tuple[bytes, list]]:
    """Rows (doc_id, held_out, text) in blocks, each under a key made of its place and contents."""
    import xxhash

    held: list = []
    size = made = 0
    pid = TaskContext.get().partitionId()

    def close():
        nonlocal held, size, made
        d = xxhash.xxh128(f"{pid}/{made}")
        for i, _, t in held:
            d.update(f"{i},{len(t)};")
        out = (d.digest(), held)
        held, size, made = [], 0, made + 1
        return out

    for rb in batches:
        for i, out, t in zip(rb.column(0).to_pylist(), rb.column(1).to_pylist(), rb.column(2)):
            t = t.as_buffer().to_pybytes()
            if held and size + len(t) > block_bytes:
                yield close()
            held.append((i, out, t))
            size += len(t)
    if held:
        yield close()


QUESTION = "node binary, path long, src binary, n int, hashes binary, counts binary, texts long"
ANSWER = "node binary, path long, n int, totals binary, tokens long, types long, once long, texts long"
#: What a node keeps (kind 0: where an asker's hashes are among its own) and asks on (kind 1).
KEPT = "kind int, " + QUESTION
_QUESTION = (pa.binary(), pa.int64(), pa.binary(), pa.int32(), pa.binary(), pa.binary(), pa.int64())
_ANSWER = (pa.binary(), pa.int64(), pa.int32(), pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int64())


def _names(schema: str) -> list[str]:
    return [c.split()[0] for c in schema.split(", ")]


def _node(path: int, group: int) -> bytes:
    return path.to_bytes(8, "big") + group.to_bytes(8, "big")


def _bits(n: int) -> int:
    return GRAM_BITS if n else WORD_BITS


def _questions(src: bytes, path: int, group: int, parts: int, ranges: int, hashes: list[np.ndarray], counts: list[np.ndarray], texts: int) -> Iterator[tuple]:
    """Rows of QUESTION from one asker of a range: a row for each order and finer range."""
    for n, (h, c) in enumerate(zip(hashes, counts)):
        cuts = range_cuts(h, path, parts, ranges, _bits(n))
        for s in range(parts):
            own = h[cuts[s] : cuts[s + 1]]
            yield _node(path * parts + s, group), path * parts + s, src, n, _pack(np.diff(own, prepend=np.uint64(0))), _pack(c[cuts[s] : cuts[s + 1]]), texts if n == 0 and s == 0 else 0


def _asked(table: pa.Table, n: int) -> tuple[list[bytes], list[tuple[np.ndarray, np.ndarray]]]:
    """The askers of order ``n``, in their order, with what they ask."""
    orders, src = np.array(table.column("n")), table.column("src").to_pylist()
    mine = sorted(np.flatnonzero(orders == n).tolist(), key=lambda k: src[k])
    hs, cs = table.column("hashes"), table.column("counts")
    return [src[k] for k in mine], [(np.cumsum(_unpack(hs[k].as_py()), dtype=np.uint64), _unpack(cs[k].as_py())) for k in mine]


def _block_key(key: bytes, members: int) -> int:
    return int.from_bytes(key[:8], "big") % members


def exchange(blocks: DataFrame, order: int, fans: list[int], fan: int, asks) -> tuple[list[DataFrame], DataFrame]:
    """The questions of each step, and the answers (ANSWER) to the blocks.

    ``asks`` turns batches of ``blocks`` into rows of QUESTION.
    """
    ranges = [math.prod(fans[: k + 1]) for k in range(len(fans))]
    questions = blocks.mapInArrow(asks, QUESTION)
    steps, kept = [questions], []

    def gather(step: int):
        def run(table: pa.Table) -> pa.Table:
            path, node = table.column("path")[0].as_py(), table.column("node")[0].as_py()
            group = int.from_bytes(node[8:], "big") // fan if step + 2 < len(fans) else 0
            rows, hashes, counts = [], [], []
            for n in range(order):
                askers, asked = _asked(table, n)
                h, c, back = merged(asked)
                hashes.append(h)
                counts.append(c)
                rows += [(0, node, path, src, n, _pack(np.diff(b, prepend=0)), b"", 0) for src, b in zip(askers, back)]
            texts = sum(table.column("texts").to_pylist())
            rows += [(1, *q) for q in _questions(node, path, group, fans[step + 1], ranges[step + 1], hashes, counts, texts)]
            return pa.Table.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), (pa.int32(), *_QUESTION))], names=_names(KEPT))

        return run

    for step in range(len(fans) - 1):
        both = materialise(questions.groupBy("node").applyInArrow(gather(step), KEPT), "gathered")
        kept.append(both.where("kind = 0").drop("kind"))
        questions = both.where("kind = 1").drop("kind")
        steps.append(questions)

    def answer(table: pa.Table) -> pa.Table:
        path = table.column("path")[0].as_py()
        texts = sum(table.column("texts").to_pylist())
        rows = []
        for n in range(order):
            askers, asked = _asked(table, n)
            _, sums, back = merged(asked)
            found = (int(sums.sum()), int((sums > 0).sum()), int((sums == 1).sum()), texts)
            rows += [(src, path, n, _pack(sums[b]), *found) for src, b in zip(askers, back)]
        return pa.Table.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), _ANSWER)], names=_names(ANSWER))

    def hand_back(own: pa.Table, got: pa.Table) -> pa.Table:
        rows = []
        path = own.column("path")[0].as_py()
        for n in range(order):
            totals, found = joined(got, n)
            orders, src, back = np.array(own.column("n")), own.column("src"), own.column("hashes")
            rows += [(src[int(k)].as_py(), path, n, _pack(totals[np.cumsum(_unpack(back[int(k)].as_py())).astype(np.int64)]), *found) for k in np.flatnonzero(orders == n)]
        return pa.Table.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), _ANSWER)], names=_names(ANSWER))

    answers = questions.groupBy("node").applyInArrow(answer, ANSWER)
    for own in reversed(kept):
        answers = own.groupBy("node").cogroup(answers.groupBy("node")).applyInArrow(hand_back, ANSWER)
    return steps, answers


def joined(answers: pa.Table, n: int) -> tuple[np.ndarray, tuple[int, int, int, int]]:
    """What the finer ranges answer for order ``n``, side by side: totals, and (tokens, types, seen once, trained texts)."""
    mine = answers.filter(pc.equal(answers.column("n"), n)).sort_by("path")
    totals = [_unpack(b) for b in mine.column("totals").to_pylist()]
    found = tuple(sum(mine.column(c).to_pylist()) for c in ("tokens", "types", "once", "texts"))
    return np.concatenate(totals) if totals else np.empty(0, np.uint64), found


def score(docs: DataFrame, *, order: int = ORDER, folds: int = FOLDS, held_out: int = HELD_OUT, block_bytes: int = BLOCK_BYTES, fan: int = FAN, shards: int | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score.

    The model learns from the texts outside fold ``held_out`` of ``folds``.
    ``shards`` sets the ranges of the last step.
    """
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), (fold_of(F.col(doc_id), folds) == held_out).alias("held_out"), text_bytes(text).alias("text"))
    if "Exchange" in rows._jdf.queryExecution().executedPlan().toString():
        rows = materialise(rows, "texts")
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    members = max(1, -(-size // block_bytes))
    fans = fan_outs(members, fan)
    if shards:
        fans[-1] = shards

    def ask(batches):
        for key, held in _blocks(batches, block_bytes):
            block = Block([t for _, _, t in held], order)
            train = np.array([not out for _, out, _ in held], bool)
            group = _block_key(key, members) // fan if len(fans) > 1 else 0
            found = list(_questions(key, 0, group, fans[0], fans[0], block.hashes, block.counts(train), int(train.sum())))
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*found), _QUESTION)], _names(QUESTION))

    def carry(batches):
        import zstandard

        for key, held in _blocks(batches, block_bytes):
            body = zstandard.ZstdCompressor(level=3).compress(b"".join(t for _, _, t in held))
            yield pa.RecordBatch.from_arrays(
                [pa.array([key], pa.binary()), pa.array([[i for i, _, _ in held]], pa.list_(pa.int64())), pa.array([[o for _, o, _ in held]], pa.list_(pa.bool_())), pa.array([[len(t) for _, _, t in held]], pa.list_(pa.int64())), pa.array([body], pa.binary())],
                ["node", "ids", "outs", "sizes", "body"],
            )

    def finish(texts: pa.Table, answers: pa.Table) -> pa.Table:
        import zstandard

        names = ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"]
        kinds = (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64())
        if texts.num_rows != 1 or answers.num_rows != order * fans[0]:
            raise ValueError("a block of texts and its n-gram counts do not match: the input's rows changed between two scans; materialise it first")
        sizes = np.array(texts.column("sizes")[0].as_py(), np.int64)
        ends = np.cumsum(sizes)
        body = zstandard.ZstdDecompressor().decompress(texts.column("body")[0].as_py(), max_output_size=max(1, int(ends[-1])))
        block = Block([body[e - n : e] for e, n in zip(ends, sizes)], order)
        del body
        totals, found = zip(*[joined(answers, n) for n in range(order)])
        if any(len(t) != len(h) for t, h in zip(totals, block.hashes)):
            raise ValueError("a block's n-gram counts do not match its texts")
        machine = Automaton(block, [t.astype(np.int64) for t in totals], np.array([f[:3] for f in found]), found[0][3])
        token = block.at[0]
        add = lambda x: np.add.reduceat(x, block.starts)
        made = (texts.column("ids")[0].as_py(), texts.column("outs")[0].as_py(), block.lengths, add(machine.known[token].astype(np.int64)), np.full(len(sizes), machine.tokens), add(machine.base[token]), add(machine.read()))
        return pa.Table.from_arrays([pa.array(x, k) for x, k in zip(made, kinds)], names=names)

    _, answers = exchange(rows, order, fans, fan, ask)
    bodies = rows.mapInArrow(carry, "node binary, ids array<long>, outs array<boolean>, sizes array<long>, body binary")
    return bodies.groupBy("node").cogroup(answers.groupBy("node")).applyInArrow(finish, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
