import math
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from rowsketch.llm import language_model as L


def plain(docs, order):
    """The model by dictionaries."""
    words = lambda t: [w for w in (t or "").encode().lower().split()] + [b"\n"]
    held = [zlib.crc32(b"" if i is None else str(i).encode()) % 5 == 1 for i, _ in docs]
    grams = [Counter() for _ in range(order)]
    begins = 0
    for (_, t), out in zip(docs, held):
        if out:
            continue
        begins += 1
        w = [b"\t", *words(t)]
        for k in range(1, len(w)):
            for n in range(1, order + 1):
                if n == 1 or k - n + 1 >= 0:
                    grams[n - 1][tuple(w[k - n + 1 : k + 1])] += 1
    N, V = sum(grams[0].values()), len(grams[0])
    share = [min(max(sum(c == 1 for c in g.values()) / max(sum(g.values()), 1), 1e-6), 1.0) for g in grams]
    out = []
    for (i, t), h in zip(docs, held):
        w = [b"\t", *words(t)]
        base = score = 0.0
        known = 0
        for k in range(1, len(w)):
            c = grams[0][(w[k],)]
            known += c > 0
            p = (c + 0.5) / (N + 0.5 * (V + 1))
            base += math.log10(p)
            for n in range(2, order + 1):
                if k - n + 1 < 0:
                    break
                hist = tuple(w[k - n + 1 : k])
                total = begins if hist == (b"\t",) else grams[n - 2][hist]
                if total:
                    p = (1 - share[n - 1]) * grams[n - 1][(*hist, w[k])] / total + share[n - 1] * p
            score += math.log10(p)
        out.append((i, h, len(w) - 1, known, N, base, score))
    return out


def test_matches_dictionaries(documents):
    some = [(r["doc_id"], r["text"]) for r in documents.collect()]
    want = {r[0]: r for r in plain(some, 3)}
    for order, block in ((3, 60_000), (3, 8_000_000)):
        got = L.score(documents, order=order, block_bytes=block, shards=5).collect()
        assert len(got) == len(some)
        for r in got:
            w = want[r["doc_id"]]
            assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == w[1:5]
            assert math.isclose(r["base_score"], w[5], rel_tol=1e-9) and math.isclose(r["score"], w[6], rel_tol=1e-9)


def test_beats_the_base_on_held_out_texts(documents):
    rows = [r for r in L.score(documents).collect() if r["held_out"]]
    assert sum(r["score"] for r in rows) > sum(r["base_score"] for r in rows)


def test_probabilities_add_up():
    """After any history, the arcs of all known words and one unknown word sum to one."""
    texts = [b"a b a c", b"a b b", b"c c a"]
    block = L.Block([*texts, *[h + b" " + w for h in (b"a", b"b", b"c") for w in (b"a", b"b", b"c", b"z")]], 2)
    train = np.array([True] * 3 + [False] * 12)
    counts = block.counts(train)
    stats = np.array([[int(c.sum()), int((c > 0).sum()), int((c == 1).sum())] for c in counts])
    logs = L.Automaton(block, [c.astype(np.int64) for c in counts], stats, 3).read()
    second = np.power(10.0, logs[block.starts + 1])[3:].reshape(3, 4).sum(axis=1)
    end = []
    for h in (b"a", b"b", b"c"):
        b2 = L.Block([*texts, h], 2)
        c2 = b2.counts(np.array([True] * 3 + [False]))
        m = L.Automaton(b2, [c.astype(np.int64) for c in c2], stats, 3).read()
        end.append(10 ** m[-1])
    assert np.allclose(second + np.array(end), 1.0)


def test_odd_rows(odd, none):
    got = L.score(odd).collect()
    assert len(got) == odd.count()
    empty = [r for r in got if r["doc_id"] in (2, 3, 4)]
    assert all(r["n_tokens"] == 1 for r in empty)
    assert L.score(none).count() == 0


def test_many_steps_of_ranges_give_the_same(documents):
    want = {r["doc_id"]: r for r in L.score(documents).collect()}
    assert L.fan_outs(20, 3) == [3, 3, 8] and L.fan_outs(256) == [683] and L.fan_outs(257) == [256, 8]
    got = L.score(documents, block_bytes=20_000, fan=3).collect()
    assert len(got) == len(want)
    for r in got:
        w = want[r["doc_id"]]
        assert r["train_tokens"] == w["train_tokens"] and r["n_known"] == w["n_known"] and math.isclose(r["score"], w["score"], rel_tol=1e-9)


def test_messages_grow_as_the_input(spark, documents):
    """Rows that the steps exchange, at two sizes: in proportion to the blocks, whatever the number of steps."""
    one = documents.select("text").coalesce(1)

    def messages(times, block_bytes=8000, fan=4):
        rows = one.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(times)))).select(F.col("k").cast("long").alias("doc_id"), F.lit(False).alias("held_out"), F.encode("text", "utf-8").alias("text"))
        size = rows.agg(F.sum(F.octet_length("text"))).first()[0]
        members = -(-size // block_bytes)
        fans = L.fan_outs(members, fan)

        def ask(batches):
            for key, held in L._blocks(batches, block_bytes):
                b = L.Block([t for _, _, t in held], 2)
                group = L._block_key(key, members) // fan if len(fans) > 1 else 0
                found = list(L._questions(key, 0, group, fans[0], fans[0], b.hashes, b.counts(np.ones(len(held), bool)), len(held)))
                yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*found), L._QUESTION)], L._names(L.QUESTION))

        steps, answers = L.exchange(rows, 2, fans, fan, ask)
        return [s.count() for s in steps], answers.count(), members

    small, back, m = messages(1)
    large, back2, m2 = messages(8)
    assert len(large) > len(small) and 6 < m2 / m < 10
    assert max(large) <= 1.5 * (m2 / m) * max(small) and back2 <= 1.5 * (m2 / m) * back


def test_the_automaton_by_dictionaries(documents):
    """States, arcs and failure arcs spelt out as words; one walk with a state over each text."""
    texts = [r["text"].encode() for r in documents.where("text is not null").orderBy("doc_id").limit(40).collect()]
    train = [k % 4 != 1 for k in range(len(texts))]
    block = L.Block(texts, 3)
    counts = [c.astype(np.int64) for c in block.counts(np.array(train))]
    stats = np.array([[int(c.sum()), int((c > 0).sum()), int((c == 1).sum())] for c in counts])
    machine = L.Automaton(block, counts, stats, sum(train))
    grams = [Counter() for _ in range(3)]
    for t, own in zip(texts, train):
        w = [b"\t", *t.lower().split(), b"\n"]
        for k in range(1, len(w)):
            for n in range(1, min(3, k + 1) + 1):
                if own:
                    grams[n - 1][tuple(w[k - n + 1 : k + 1])] += 1
    N, V = sum(grams[0].values()), len(grams[0])
    share = [sum(c == 1 for c in g.values()) / sum(g.values()) for g in grams]
    states = {(), (b"\t",), *grams[0], *grams[1]}

    def arc(g):
        if len(g) == 1:
            return (grams[0][g] + 0.5) / (N + 0.5 * (V + 1))
        total = sum(train) if g[:-1] == (b"\t",) else grams[len(g) - 2][g[:-1]]
        return (1 - share[len(g) - 1]) * grams[len(g) - 1][g] / total + share[len(g) - 1] * arc(g[1:])

    want = []
    for t in texts:
        state = (b"\t",)
        for w in [*t.lower().split(), b"\n"]:
            log = 0.0
            while state and not grams[len(state)][(*state, w)]:
                log += math.log10(share[len(state)])
                state = state[1:]
                while state not in states:
                    state = state[1:]
            g = (*state, w)
            want.append(log + math.log10(arc(g)))
            state = g[-2:]
            while state not in states:
                state = state[1:]
    for stretch in (3, 7, 256, 10**6):
        assert np.allclose(machine.read(stretch), want, rtol=1e-12, atol=1e-12)


def test_a_shuffled_input(documents):
    want = {r["doc_id"]: r["score"] for r in L.score(documents).collect()}
    got = {r["doc_id"]: r["score"] for r in L.score(documents.repartition(3, "lang")).collect()}
    assert want.keys() == got.keys() and all(math.isclose(want[k], got[k], rel_tol=1e-9) for k in want)
