import numpy as np
import pytest

from rowsketch.llm import simhash


def plain(text):
    import xxhash

    w = (text or "").encode().lower().split()
    if not w:
        return 0
    s = [b" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))]
    h = [xxhash.xxh64_intdigest(x, seed=42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def components(fps, ids, bits=3):
    label = list(ids)
    while True:
        new = [min(label[j] for j in range(len(fps)) if (fps[i] ^ fps[j]).bit_count() <= bits) for i in range(len(fps))]
        if new == label:
            return label
        label = new


@pytest.mark.parametrize("hot", [100_000, 3])
def test_matches_brute_force(make, hot):
    rng = np.random.default_rng(1)
    base = [" ".join(rng.choice(["alpha", "beta", "gamma", "delta", "eps", "zeta"], 60)) for _ in range(20)]
    docs = [(k, b) for k, b in enumerate(base)] + [(100 + k, b + " tail" * (k % 3)) for k, b in enumerate(base)] + [(300, None), (301, ""), (302, "A  b"), (303, "a b")]
    got = {r["doc_id"]: r for r in simhash.near_duplicates(make(docs), hot=hot).withColumn("hex", simhash.hex_fingerprint()).collect()}
    fps = [plain(t) for _, t in docs]
    want = components(fps, [i for i, _ in docs])
    for (i, _), f, c in zip(docs, fps, want):
        assert got[i]["hex"] == f"{f:016x}" and got[i]["component_id"] == c
    assert got[301]["component_id"] == 300 and got[303]["component_id"] == 302


def test_trie_finds_every_link():
    rng = np.random.default_rng(2)
    seeds = rng.integers(0, 2**63, 40, dtype=np.uint64)
    fps = list(seeds)
    for s in seeds:
        for _ in range(30):
            x = int(s)
            for b in rng.choice(64, rng.integers(1, 6), replace=False):
                x ^= 1 << int(b)
            fps.append(np.uint64(x))
    fps = np.unique(np.array(fps, np.uint64))
    label = simhash.trie_links(fps, np.array([0]), np.array([len(fps)]), 3)
    want = components([int(x) for x in fps], range(len(fps)))
    assert label.tolist() == want


def test_components_of_a_chain(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(1, 12)] + [(100, 101), (5, 5)], "a long, b long")
    got = {r["node"]: r["root"] for r in simhash.components(edges).collect()}
    assert got == {k: 1 for k in range(1, 13)} | {100: 100, 101: 100}


def test_keep_first(make, odd, none):
    docs = make([(5, "one two three four"), (2, "one two three four"), (9, "quite another text here"), (2, "one two three four"), (None, "one two three four")])
    assert sorted(str(r["doc_id"]) for r in simhash.keep_first(docs).collect()) == ["2", "9", "None"]
    assert simhash.keep_first(odd).columns == odd.columns
    assert simhash.keep_first(none).count() == 0 and simhash.near_duplicates(none).count() == 0
    assert simhash.near_duplicates(odd).count() == odd.count()


def test_rows_of_one_id_are_judged_apart(make):
    docs = make([(2, ""), (5, "unique text"), (5, "")])
    assert sorted((r["doc_id"], r["text"]) for r in simhash.keep_first(docs).collect()) == [(2, ""), (5, "unique text")]


def five(text):
    w = (text or "").encode().lower().split()
    return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()


def kept_by_brute_force(docs):
    """(id, text) of the least (id, text hash) of each component of equal and similar texts."""
    texts = sorted({t or "" for _, t in docs}, key=lambda t: min((i for i, x in docs if (x or "") == t)))
    sets = [five(t) for t in texts]
    label = list(range(len(texts)))
    while True:
        new = [min(label[j] for j in range(len(texts)) if j == k or sets[k] and 5 * len(sets[k] & sets[j]) >= 4 * len(sets[k] | sets[j])) for k in range(len(texts))]
        if new == label:
            break
        label = new
    return sorted((min(i for i, x in docs if (x or "") == t), t) for k, t in enumerate(texts) if label[k] == k)


def similar_docs(seed):
    rng = np.random.default_rng(seed)
    docs = []
    for k in range(30):
        w = list(rng.integers(0, 5000, 200).astype(str))
        docs.append((k, " ".join(w)))
        for copy in range(4):  # up to four words changed: similarity 0.82 and up; some of eight: below
            v = list(w)
            for at in rng.choice(200, (1, 2, 4, 8)[copy], replace=False):
                v[at] = f"x{rng.integers(10**6)}"
            docs.append((100 + 4 * k + copy, " ".join(v)))
    return docs


def test_keep_similar_matches_brute_force(make):
    docs = similar_docs(7) + [(900, None), (901, ""), (902, "a b c"), (903, "A  b c"), (904, "a b d")]
    got = sorted((r["doc_id"], r["text"] or "") for r in simhash.keep_similar(make(docs)).collect())
    assert got == kept_by_brute_force(docs)
    assert 900 in [i for i, _ in got] and 901 not in [i for i, _ in got] and 903 not in [i for i, _ in got]


def test_keep_similar_odd_rows(make, odd, none):
    docs = make([(2, ""), (5, "unique text"), (5, ""), (7, "unique text"), (None, "unique text"), (5, "unique text")])
    assert sorted((str(r["doc_id"]), r["text"]) for r in simhash.keep_similar(docs).collect()) == [("2", ""), ("5", "unique text"), ("None", "unique text")]
    assert simhash.keep_similar(odd).columns == odd.columns and simhash.keep_similar(none).count() == 0


def test_large_groups_are_searched_whole():
    fps = np.repeat(np.arange(3, dtype=np.uint64)[:, None] * np.uint64(0x5555555555555555), 2, axis=1)
    fps = np.concatenate([fps[[k % 3]] ^ np.uint64(1 << k % 16) for k in range(simhash.LARGE + 90)])
    label = dict(enumerate(simhash._filter_links(fps, np.arange(len(fps)), np.array([0]), np.array([len(fps)])).tolist()))
    near = lambda k: min(j for j in range(len(fps)) if int(np.bitwise_count(fps[j] ^ fps[k]).sum()) <= simhash.NEAR)
    assert all(label[k] == near(k) for k in label)


def test_a_task_sends_one_edge_a_node(spark):
    """Near copies in one large group, and in many small ones, join without their pairs leaving the task."""
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**63, 2, np.int64)
    rows = []
    for node in range(900):
        words = [int(base[w] ^ (1 << int(rng.integers(0, 60)))) for w in range(2)]
        rows += [(key, node, *words) for key in (7, 100 + node // 300, 1000 + node // 20)]
    dealt = spark.createDataFrame(rows, "key int, node long, w0 long, w1 long")
    edges = simhash._wide_links(dealt).collect()
    parts = 4  # shuffle partitions of the session
    assert len(edges) < 900 * parts
    roots = {r["node"]: r["root"] for r in simhash.components(simhash._wide_links(dealt)).collect()}
    assert len(roots) == 900 and set(roots.values()) == {0}


@pytest.mark.parametrize("most", [12, 90, 700])
def test_wide_candidates_come_from_the_trie(monkeypatch, most):
    """Groups of wide fingerprints go through the trie self-join, which finds the links of all pairs."""
    rng, calls = np.random.default_rng(most), []
    sizes = rng.integers(1, most, 30 if most < 100 else 4)
    ends = np.cumsum(sizes)
    starts, n = ends - sizes, int(ends[-1])
    fps = rng.integers(0, 2**63, (max(2, n // 5), 2), np.int64).view(np.uint64)[rng.integers(0, max(2, n // 5), n)]
    for r in range(n):
        for b in rng.integers(0, 128, rng.integers(0, 30)):
            fps[r, b // 64] ^= np.uint64(1) << np.uint64(b % 64)
    member = rng.integers(0, n, n)
    walk = simhash.trie_links
    monkeypatch.setattr(simhash, "trie_links", lambda *a: calls.append(1) or walk(*a))
    want = simhash.Labels(int(member.max()) + 1)
    for a, b in zip(starts, ends):
        i, j = np.triu_indices(b - a, 1)
        near = np.bitwise_count(fps[a + i] ^ fps[a + j]).sum(axis=1) <= simhash.NEAR
        want.join(member[a + i[near]], member[a + j[near]])
    assert simhash._filter_links(fps, member, starts, ends).tolist() == want.of.tolist() and calls


def test_near_copies_do_not_become_pairs():
    """Thousands of near copies in one group are joined without comparing each with each."""
    rng = np.random.default_rng(5)
    fps = np.repeat(rng.integers(0, 2**63, (1, 2), np.int64).view(np.uint64), 20_000, axis=0)
    for w in range(2):
        for _ in range(3):
            fps[:, w] ^= np.uint64(1) << rng.integers(0, 64, len(fps)).astype(np.uint64)
    compared = []
    count = np.bitwise_count
    try:
        np.bitwise_count = lambda x: compared.append(len(x)) or count(x)
        label = simhash._filter_links(fps, np.arange(len(fps)), np.array([0]), np.array([len(fps)]))
    finally:
        np.bitwise_count = count
    assert not label.any() and sum(compared) < 50 * len(fps)
