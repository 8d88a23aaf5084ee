"""SimHash near-duplicates by a binary-trie self-join.

Fingerprints are 64 bits over repeated word shingles.  Distinct fingerprints
within ``bits`` differing bits agree wholly on one of ``bits + 1`` blocks, so
they are dealt out by (block, its value).  Inside a group the sorted
fingerprints are an implicit binary trie: node pairs are walked down together,
differing bits add up, and a pair is dropped as soon as the budget is spent.
Each task joins what it links and passes on one edge a fingerprint at most, so
a large group of near copies never becomes all of its pairs.  A group of more
than ``hot`` fingerprints is dealt anew by blocks of its remaining bits, which
is exact by the same argument.  Components over the edges are found with
alternating star contraction, in tables of the shared folder.

Null and empty texts have fingerprint zero and are linked like any other; equal
texts meet at one fingerprint and cost nothing more; a component without any
non-null id has a null id; repeated rows get a row each; an empty table gives an
empty result; other columns are not read by :func:`near_duplicates` and pass
through :func:`keep_first`.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowsketch.llm.common import free_name, named, release, text_bytes
from rowsketch.shared import discard, materialise

SHINGLE = 3
SEED = 42
BITS = 3
HOT = 100_000
#: Words of a shingle, and the share of shingles in common, from which two texts of :func:`keep_similar` are one.
SIMILAR_SHINGLE = 5
SIMILARITY = 0.8
#: Bits of a wide fingerprint in 64-bit words, of each key cut from it, and how many may differ in the first FILTER words.
WIDE = 8
KEY_BITS = 14
FILTER = 2
NEAR = 36
#: Rows of a group from which neighbours in a trie's order are joined before the walk.
LARGE = 512
#: Shingles hashed before their bits are summed.
STEP = 65_536
#: Node pairs handled at once.
FRONTIER = 1_000_000


def fingerprint(text: bytes, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """Majority bits over the XXH64 of all shingles, repeats included."""
    import xxhash

    words = text.lower().split()
    if not words:
        return 0
    h = xxhash.xxh64_intdigest
    n = max(1, len(words) - shingle + 1)
    counts = np.zeros(64, np.int64)
    for at in range(0, n, STEP):
        if len(words) < shingle:
            shingles = [b" ".join(words)]
        else:
            part = words[at : at + STEP + shingle - 1]
            shingles = map(b" ".join, zip(*[part[k:] for k in range(shingle)]))
        values = np.array([h(s, seed) for s in shingles], np.uint64)
        counts += np.unpackbits(values.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > n).tobytes(), "big")


def text_key(text: str = "text"):
    """64 bits that stand for a whole text; null counts as empty."""
    return F.xxhash64(text_bytes(text))


def fingerprints(docs: DataFrame, *, shingle: int = SHINGLE, seed: int = SEED, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp, text_key): the fingerprint as a signed long with the same bits, and the text's hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            made = np.fromiter((fingerprint(t.as_buffer().to_pybytes(), shingle, seed) for t in rb.column(1)), np.uint64, rb.num_rows)
            yield pa.RecordBatch.from_arrays([rb.column(0), pa.array(made.view(np.int64)), rb.column(2)], ["doc_id", "fp", "text_key"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), text_bytes(text).alias("text"), text_key(text).alias("text_key")).mapInArrow(run, "doc_id long, fp long, text_key long")


class Labels:
    """Components of 0 .. n-1, each under its least member, as links come in."""

    def __init__(self, n: int):
        self.of = np.arange(n)

    def join(self, i: np.ndarray, j: np.ndarray) -> None:
        while True:
            a, b = self.of[i], self.of[j]
            differ = a != b
            if not differ.any():
                return
            i, j, a, b = i[differ], j[differ], a[differ], b[differ]
            np.minimum.at(self.of, np.maximum(a, b), np.minimum(a, b))
            while True:
                up = self.of[self.of]
                if (up == self.of).all():
                    break
                self.of = up


def trie_links(fps: np.ndarray, starts: np.ndarray, ends: np.ndarray, bits: int, member: np.ndarray | None = None) -> np.ndarray:
    """Component labels of the links inside each group, of rows or, with ``member``, of the members 0 .. m-1 whose rows they are.

    ``fps``: unsigned fingerprints, of one word or (rows x words) of several,
    the first word leading, ascending within each group [start, end).
    A node is an interval of rows with one prefix; a node pair carries the
    bits in which its prefixes differ.  With ``member`` a pair of nodes that
    are of one component throughout is not walked any further, and in groups
    of more than LARGE rows neighbours are joined before the walk, so a large
    group of near copies never becomes its pairs.
    """
    words = [fps] if fps.ndim == 1 else [np.ascontiguousarray(w) for w in fps.T]
    n, own_rows = len(fps), member is None
    member = np.arange(n) if own_rows else member
    labels = Labels(int(member.max()) + 1 if len(member) else 0)
    frontier = FRONTIER if own_rows else FRONTIER // 16
    large = starts[:0] if own_rows else starts[ends - starts > LARGE]
    ones: dict[int, np.ndarray] = {}

    def cut(bit: int, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Where the rows with this bit set begin, in each interval."""
        if bit not in ones:
            if len(ones) >= 64 // len(words):
                ones.clear()
            word = words[len(words) - 1 - bit // 64]
            ones[bit] = np.concatenate([[0], np.cumsum((word >> np.uint64(bit % 64)) & np.uint64(1), dtype=np.int64)]).astype(np.int32)
        c = ones[bit]
        return hi - (c[hi] - c[lo])

    def apart(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        out = np.bitwise_count(words[0][i] ^ words[0][j])
        for w in words[1:]:
            out = out + np.bitwise_count(w[i] ^ w[j]).astype(np.int16)
        return out

    def resolve(a: np.ndarray, b: np.ndarray, c: np.ndarray, d: np.ndarray) -> None:
        """Compares the rows of small node pairs directly, some at a time."""
        sizes = (b - a) * (d - c)
        total = np.cumsum(sizes)
        at = 0
        while at < len(sizes):
            to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + 4 * frontier, "right")))
            s = sizes[at:to]
            k = np.repeat(np.arange(at, to), s)
            off = np.arange(len(k)) - np.repeat(np.cumsum(s) - s, s)
            width = (d - c)[k]
            i, j = a[k] + off // width, c[k] + off % width
            near = (i < j) & (apart(i, j) <= bits)
            labels.join(member[i[near]], member[j[near]])
            at = to

    def joined(a: np.ndarray, b: np.ndarray, c: np.ndarray, d: np.ndarray) -> np.ndarray:
        """Which node pairs are of one component throughout."""
        label = labels.of[member]
        turn = np.concatenate([[0], np.cumsum(label[1:] != label[:-1])])
        return (turn[a] == turn[b - 1]) & (turn[c] == turn[d - 1]) & (label[a] == label[c])

    for start, end in zip(large, ends[ends - starts > LARGE] if len(large) else large):
        i = np.arange(start, end - 1)
        i = i[apart(i, i + 1) <= bits]
        labels.join(member[i], member[i + 1])
    small = 64
    stack = [(64 * len(words) - 1, starts.astype(np.int64), ends.astype(np.int64), starts.astype(np.int64), ends.astype(np.int64), np.zeros(len(starts), np.int8))]
    while stack:
        bit, a, b, c, d, spent = stack.pop()
        if len(large):
            rest = ~joined(a, b, c, d)
            a, b, c, d, spent = a[rest], b[rest], c[rest], d[rest], spent[rest]
        tiny = (b - a) * (d - c) <= small
        if bit < 0:
            tiny[:] = True
        if tiny.any():
            resolve(a[tiny], b[tiny], c[tiny], d[tiny])
            rest = ~tiny
            a, b, c, d, spent = a[rest], b[rest], c[rest], d[rest], spent[rest]
        if not len(a):
            continue
        if len(a) > frontier:
            h = len(a) // 2
            stack += [(bit, a[:h], b[:h], c[:h], d[:h], spent[:h]), (bit, a[h:], b[h:], c[h:], d[h:], spent[h:])]
            continue
        m, k = cut(bit, a, b), cut(bit, c, d)
        own = (a == c) & (b == d)
        pairs = [(a, m, c, k, spent, None), (m, b, k, d, spent, None), (a, m, k, d, spent + 1, None), (m, b, c, k, spent + 1, ~own)]
        grown = []
        for x0, x1, y0, y1, s, only in pairs:
            live = (x1 > x0) & (y1 > y0) & (s <= bits)
            if only is not None:
                live &= only
            grown.append((x0[live], x1[live], y0[live], y1[live], s[live]))
        nxt = [np.concatenate(z) for z in zip(*grown)]
        stack.append((bit - 1, *nxt))
    return labels.of


def _parts(mask: int, parts: int) -> list[int]:
    """Masks that add to ``mask`` one of ``parts`` runs of its free bits, each."""
    free = [b for b in range(63, -1, -1) if not mask >> b & 1]
    out = []
    for k in range(parts):
        run = free[k * len(free) // parts : (k + 1) * len(free) // parts]
        out.append(mask | sum(1 << b for b in run))
    return out


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def links(distinct: DataFrame, bits: int = BITS, hot: int = HOT) -> DataFrame:
    """(a, b): edges that join all fingerprints ``fp`` within ``bits`` bits, a forest in each task."""
    masks = _parts(0, bits + 1)
    dealt = distinct.select("fp", F.explode(F.array(*[F.lit(_signed(m)) for m in masks])).alias("mask")).select("fp", "mask", F.col("fp").bitwiseAND(F.col("mask")).alias("key"))
    found = None
    while True:
        sizes = dealt.groupBy("mask", "key").count().where(F.col("count") > hot)
        over = sizes.limit(1).count() > 0 and any(m != (1 << 64) - 1 for m in masks)
        now = dealt.join(sizes, ["mask", "key"], "left_anti") if over else dealt
        edges = _task_links(now, bits)
        found = edges if found is None else found.unionByName(edges)
        if not over:
            return found
        children = {m: _parts(m, bits + 1) for m in masks}
        options = F.create_map(*[x for m, c in children.items() for x in (F.lit(_signed(m)), F.array(*[F.lit(_signed(y)) for y in c]))])
        dealt = materialise(dealt.join(sizes.select("mask", "key"), ["mask", "key"]).select("fp", F.explode(options[F.col("mask")]).alias("mask")).select("fp", "mask", F.col("fp").bitwiseAND(F.col("mask")).alias("key")).distinct(), "hot-groups")
        masks = sorted({y for c in children.values() for y in c})


def _task_links(dealt: DataFrame, bits: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [(rb.column(0).to_numpy(), rb.column(1).to_numpy(), rb.column(2).to_numpy()) for rb in batches if rb.num_rows]
        if not parts:
            return
        fp, mask, key = (np.concatenate(x) for x in zip(*parts))
        fp = fp.view(np.uint64)
        order = np.lexsort((fp, key, mask))
        fp, mask, key = fp[order], mask[order], key[order]
        first = np.flatnonzero(np.concatenate([[True], (mask[1:] != mask[:-1]) | (key[1:] != key[:-1])]))
        last = np.concatenate([first[1:], [len(fp)]])
        many = last - first > 1
        label = trie_links(fp, first[many], last[many], bits)
        moved = np.flatnonzero(label != np.arange(len(label)))
        yield pa.RecordBatch.from_arrays([pa.array(fp[moved].view(np.int64)), pa.array(fp[label[moved]].view(np.int64))], ["a", "b"])

    spread = dealt.select("fp", "mask", "key").repartition(F.col("mask"), F.col("key"))
    return spread.mapInArrow(run, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """(node, root): the least node of each component, for every node with an edge.

    Alternating large-star and small-star steps; only minima are aggregated, so
    a node with many edges is summed on the map side.
    """
    now = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    before = None
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        hung = large.join(least, "u")
        small = hung.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v"))).distinct()
        last, now = now, materialise(small, "stars")
        discard(last)
        state = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
        before = state


def _labelled(docs: DataFrame, *, bits: int = BITS, shingle: int = SHINGLE, seed: int = SEED, hot: int = HOT, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp, text_key, component_id), a row for each row of ``docs``."""
    rows = materialise(fingerprints(docs, shingle=shingle, seed=seed, doc_id=doc_id, text=text), "fingerprints")
    by_fp = materialise(rows.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct-fingerprints")
    roots = components(links(by_fp.select("fp"), bits, hot)).withColumnRenamed("node", "fp")
    linked = by_fp.join(roots, "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    lowest = linked.groupBy("root").agg(F.min("least").alias("component_id"))
    of_fp = linked.join(lowest, "root").select("fp", "component_id")
    return rows.join(of_fp, "fp").select("doc_id", "fp", "text_key", "component_id")


def near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, fp, component_id): the least id that links of at most ``bits`` bits reach."""
    return _labelled(docs, **options).select("doc_id", "fp", "component_id")


def hex_fingerprint(fp="fp"):
    return F.lpad(F.lower(F.hex(F.col(fp))), 16, "0")


def _without(docs: DataFrame, rows: DataFrame, gone: DataFrame, doc_id: str, text: str) -> DataFrame:
    """``docs`` without the (doc_id, text_key) of ``gone``, and once each (id, text) of ``rows`` that repeats."""
    names = [named(c) for c in docs.columns]
    key, gone_id, gone_key = (free_name(docs.columns, c) for c in ("dedup_key", "dedup_id", "dedup_gone"))
    gone = gone.select(F.col("doc_id").alias(gone_id), F.col("text_key").alias(gone_key)).distinct()
    keyed = docs.select(*names, text_key(text).alias(key))
    kept = keyed.join(gone, (named(doc_id) == F.col(gone_id)) & (F.col(key) == F.col(gone_key)), "left_anti")
    if not rows.where(F.col("doc_id").isNotNull()).groupBy("doc_id", "text_key").count().where("count > 1").limit(1).count():
        return kept.select(*names)
    # summed up on the map side, so that a row which very many repeat is no large group
    once = kept.where(named(doc_id).isNotNull()).dropDuplicates([doc_id, key])
    return once.unionByName(kept.where(named(doc_id).isNull())).select(*names)


def keep_first(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """One document of each group stays: the one with the least id, whole and unchanged.

    A row with a null id stays.  Rows that share id and text are one document;
    rows that share an id but not the text are judged apart.
    """
    found = _labelled(docs, doc_id=doc_id, text=text, **options)
    return _without(docs, found, found.where(F.col("component_id") < F.col("doc_id")), doc_id, text)


def shingle_set(text: bytes, shingle: int = SIMILAR_SHINGLE, seed: int = SEED) -> np.ndarray:
    """Sorted distinct XXH64 values of a text's word shingles; a shorter text is one shingle, an empty one none."""
    import xxhash

    words = text.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    h = xxhash.xxh64_intdigest
    shingles = set(map(b" ".join, zip(*[words[k:] for k in range(shingle)]))) if len(words) >= shingle else {b" ".join(words)}
    return np.unique(np.fromiter((h(s, seed) for s in shingles), np.uint64, len(shingles)))


def wide_fingerprint(values: np.ndarray) -> np.ndarray:
    """Majority bits over a shingle set, WIDE words of 64 independent bits."""
    out = np.zeros((WIDE, 8), np.uint8)
    for w in range(WIDE):
        counts = np.zeros(64, np.int64)
        for at in range(0, len(values), STEP):
            with np.errstate(over="ignore"):
                x = values[at : at + STEP] + np.uint64(w) * np.uint64(0x9E3779B97F4A7C15)
                for shift, mul in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
                    x = (x ^ (x >> np.uint64(shift))) * np.uint64(mul)
                x ^= x >> np.uint64(31)
            bits = np.unpackbits(x.view(np.uint8).reshape(-1, 8), axis=1)
            for low in range(0, len(bits), 128):  # sums of bytes stay bytes
                counts += bits[low : low + 128].sum(axis=0, dtype=np.uint8)
        out[w] = np.packbits(2 * counts > len(values))
    return out.reshape(-1).view(np.uint64)


def _keys(wide: np.ndarray) -> np.ndarray:
    """Each fingerprint's keys: its bits cut into runs of KEY_BITS, numbered by place."""
    bits = np.unpackbits(np.ascontiguousarray(wide).view(np.uint8).reshape(len(wide), -1), axis=1)
    places = bits.shape[1] // KEY_BITS
    runs = bits[:, : places * KEY_BITS].reshape(len(wide), places, KEY_BITS)
    return runs @ (1 << np.arange(KEY_BITS)) + (np.arange(places) << KEY_BITS)


def _spread_out(start: int, found: np.ndarray, near) -> None:
    """Labels in ``found`` (-1: not seen) every row reached from ``start``; ``near(i, rows)`` says which rows i links to."""
    found[start] = start
    queue = [start]
    unseen = np.flatnonzero(found < 0)
    while queue and len(unseen):
        hit = near(queue.pop(), unseen)
        found[unseen[hit]] = start
        queue += unseen[hit].tolist()
        unseen = unseen[~hit]


def _filter_links(fps: np.ndarray, member: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Components of the members 0 .. n-1 that rows within NEAR bits in the FILTER words join, inside each group [start, end) of rows.

    The rows of a group are sorted to a trie, which is joined with itself.
    """
    sizes = ends - starts
    group = np.repeat(np.arange(len(starts)), sizes)
    to = np.cumsum(sizes)
    rows = np.arange(len(group)) + (starts - (to - sizes))[group]
    rows = rows[np.lexsort((*fps[rows].T[::-1], group))]
    label = trie_links(fps[rows], to - sizes, to, NEAR, member[rows])
    # members of no group stay by themselves
    return np.concatenate([label, np.arange(len(label), int(member.max()) + 1)]) if len(member) else label


def _wide_links(dealt: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [[c.to_numpy() for c in rb.columns] for rb in batches if rb.num_rows]
        if not parts:
            return
        key, node, *words = (np.concatenate(x) for x in zip(*parts))
        order = np.argsort(key, kind="stable")
        key, node, fps = key[order], node[order], np.stack(words, axis=1)[order].view(np.uint64)
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        last = np.concatenate([first[1:], [len(key)]])
        many = last - first > 1
        nodes, member = np.unique(node, return_inverse=True)
        label = _filter_links(fps, member, first[many], last[many])
        moved = np.flatnonzero(label != np.arange(len(label)))  # a node has one edge at most
        yield pa.RecordBatch.from_arrays([pa.array(nodes[moved]), pa.array(nodes[label[moved]])], ["a", "b"])
        del key, node, words, fps, parts, nodes, member
        release()

    return dealt.repartition("key").mapInArrow(run, "a long, b long")


def similar_labels(sets: list[np.ndarray], similarity: float = SIMILARITY) -> np.ndarray:
    """Components (row numbers) of the links between sets whose Jaccard similarity is high enough; exact."""
    size = np.array([len(s) for s in sets])
    found = np.full(len(sets), -1)

    def near(x: int, rows: np.ndarray) -> np.ndarray:
        out = np.zeros(len(rows), bool)
        fit = np.flatnonzero((np.minimum(size[rows], size[x]) >= similarity * np.maximum(size[rows], size[x]) - 1e-9) & (size[rows] > 0))
        for at in range(0, len(fit), 256):
            some = fit[at : at + 256]
            if size[x] == 0:
                break
            own = np.concatenate([sets[r] for r in rows[some]])
            place = np.minimum(np.searchsorted(sets[x], own), size[x] - 1)
            common = np.add.reduceat((sets[x][place] == own).astype(np.int64), np.concatenate([[0], np.cumsum(size[rows[some]])[:-1]]))
            out[some] = common >= similarity * (size[rows[some]] + size[x] - common) - 1e-9
        return out

    for k in range(len(sets)):
        if found[k] < 0:
            _spread_out(k, found, near)
    return found


def _verified(members: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(node, mark) of (root, node, text): nodes of one root share a mark where links of similar texts join them."""

    def judge(nodes: list[int], sets: list[np.ndarray]) -> pa.RecordBatch:
        label = similar_labels(sets, similarity)
        return pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([nodes[k] for k in label], pa.int64())], ["node", "mark"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, nodes, sets = None, [], []
        for rb in batches:
            for root, node, text in zip(rb.column(0).to_pylist(), rb.column(1).to_pylist(), rb.column(2)):
                if root != now and nodes:
                    yield judge(nodes, sets)
                    nodes, sets = [], []
                now = root
                nodes.append(node)
                sets.append(shingle_set(text.as_buffer().to_pybytes(), shingle))
        if nodes:
            yield judge(nodes, sets)
        nodes, sets = [], []
        release()

    return members.repartition("root").sortWithinPartitions("root", "node").select("root", "node", "text").mapInArrow(run, "node long, mark long")


def keep_similar(docs: DataFrame, *, shingle: int = SIMILAR_SHINGLE, similarity: float = SIMILARITY, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One document of each group stays: groups are joined by pairs of texts with a Jaccard similarity of their word shingles of ``similarity`` or more.

    Candidates agree on one of 36 keys of 14 bits of a SimHash of 512 bits;
    those of a key are a binary trie over its first 128 bits, whose self-join
    (:func:`trie_links`) has the pairs that differ in at most NEAR of them.
    What they join is then verified on the shingle sets themselves, so no text
    goes without a similar one.
    Equal texts are one.  Null ids and repeated rows as in :func:`keep_first`.
    """
    names = [f"w{k}" for k in range(FILTER)]

    def prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            made = [wide_fingerprint(shingle_set(t.as_buffer().to_pybytes(), shingle)).tobytes() for t in rb.column(2)]
            yield pa.RecordBatch.from_arrays([rb.column(0), rb.column(1), pa.array(made, pa.binary())], ["doc_id", "text_key", "fp"])
        release()

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            if not rb.num_rows:
                continue
            wide = np.frombuffer(b"".join(rb.column(1).to_pylist()), np.uint64).reshape(-1, WIDE)
            keys = _keys(wide)
            times = keys.shape[1]
            words = [pa.array(np.repeat(wide[:, k].view(np.int64), times)) for k in range(FILTER)]
            yield pa.RecordBatch.from_arrays([pa.array(keys.ravel().astype(np.int32)), pa.array(np.repeat(rb.column(0).to_numpy(), times)), *words], ["key", "node", *names])

    rows = materialise(docs.select(F.col(doc_id).cast("long").alias("doc_id"), text_key(text).alias("text_key"), text_bytes(text).alias("text")).mapInArrow(prints, "doc_id long, text_key long, fp binary"), "wide-fingerprints")
    by_text = rows.groupBy(F.col("text_key").alias("node")).agg(F.min("doc_id").alias("least"))
    dealt = rows.select("text_key", "fp").distinct().mapInArrow(deal, "key int, node long, " + ", ".join(f"{n} long" for n in names))
    roots = materialise(components(_wide_links(dealt)), "near-texts")
    texts = docs.select(text_key(text).alias("node"), text_bytes(text).alias("text"), F.col(doc_id).cast("long").alias("doc_id"))
    # one row of each text is enough to verify: the first, or any where all ids are null
    some = texts.join(roots, "node").join(by_text, "node").where("doc_id <=> least").select("root", "node", "text").dropDuplicates(["node"])
    marks = materialise(_verified(some, shingle, similarity), "verified")
    of_text = by_text.join(marks, "node", "left").select("node", "least", F.coalesce("mark", "node").alias("mark"))
    chosen = of_text.where("least is not null").groupBy("mark").agg(F.min(F.struct("least", "node")).alias("c"))
    stays = of_text.join(chosen, "mark").select(F.col("node").alias("text_key"), F.col("c.least").alias("_id"), F.col("c.node").alias("_node"))
    gone = rows.select("doc_id", "text_key").where("doc_id is not null").join(stays, "text_key").where("doc_id <> _id or text_key <> _node")
    return _without(docs, rows, gone, doc_id, text)


__all__ = ["components", "fingerprint", "fingerprints", "hex_fingerprint", "keep_first", "keep_similar", "links", "near_duplicates", "shingle_set", "similar_labels", "trie_links", "wide_fingerprint"]
