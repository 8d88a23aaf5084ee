import numpy as np
import pytest
from pyspark.sql import functions as F

from rowsketch.llm import quality_classifier as Q
from rowsketch.llm import toxicity as T


@pytest.fixture(scope="module")
def larger(spark):
    d = "/root/testdata/sf0.01"
    return spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")


def auc(score, y):
    order = np.argsort(score, kind="stable")
    rank = np.empty(len(y))
    rank[order] = np.arange(1, len(y) + 1)
    pos = y == 1
    return (rank[pos].sum() - pos.sum() * (pos.sum() + 1) / 2) / (pos.sum() * (~pos).sum())


@pytest.mark.parametrize("module,label,least", [(Q, "quality", 0.95), (T, "toxic", 0.9)])
def test_held_out_accuracy(larger, module, label, least):
    docs, labels = larger
    if module is T:  # needs more marked texts
        docs, labels = (docs.sparkSession.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    r = module.score(docs, labels).cache()
    assert r.columns == ["doc_id", "held_out", "score", "predicted"] and r.count() == docs.count()
    p = r.join(labels, "doc_id").where("held_out").toPandas()
    assert auc(p.score.to_numpy(), p[label].to_numpy()) >= least
    assert (p.predicted == p[label]).mean() >= 0.9
    assert p.score.between(0, 1).all()


@pytest.mark.parametrize("module", [Q, T])
def test_labels_of_the_held_out_fold_are_not_read(larger, module):
    docs, labels = larger
    name = "quality" if module is Q else "toxic"
    few = docs.where("doc_id < 300")
    keep = few.join(labels, "doc_id", "left")
    held = module.score(few, labels).select("doc_id", "held_out")
    turned = labels.join(held, "doc_id").withColumn(name, F.when(F.col("held_out"), 1 - F.col(name)).otherwise(F.col(name)))
    a = {r["doc_id"]: r["score"] for r in module.score(few, labels.join(held, "doc_id", "left_semi")).collect()}
    b = {r["doc_id"]: r["score"] for r in module.score(few, turned).collect()}
    assert keep.count() and all(abs(a[k] - b[k]) < 1e-9 for k in a)


@pytest.mark.parametrize("module", [Q, T])
def test_odd(odd, none, labels, module):
    r = module.score(odd, labels)
    assert r.count() == odd.count() and r.where("score is null or score < 0 or score > 1").count() == 0
    assert module.score(none, labels).count() == 0
    assert module.score(odd, labels.where("false")).count() == odd.count()


def test_keep_good(larger):
    docs, labels = larger
    kept = Q.keep_good(docs, labels)
    assert kept.columns == docs.columns
    want = {r["doc_id"] for r in Q.score(docs, labels).where("predicted = 1").collect()}
    got = kept.collect()
    assert {r["doc_id"] for r in got} == want
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert all(text[r["doc_id"]] == r["text"] for r in got)


def test_discriminant_is_the_gaussian_rule():
    rng = np.random.default_rng(1)
    x = [rng.standard_normal((4000, 3)), rng.standard_normal((4000, 3)) * [1, 2, 0.5] + [1, 0, 0]]
    n = np.array([4000.0, 4000.0])
    m = Q.fit_from_sums(n, np.array([a.sum(0) for a in x]), np.array([a.T @ a for a in x]), 0.0, 0.0, 0.0)
    at = rng.standard_normal((50, 3))
    log = []
    for a in x:
        c = np.cov(a.T, bias=True)
        d = at - a.mean(0)
        log.append(-0.5 * np.log(np.linalg.det(c)) - 0.5 * np.einsum("ij,jk,ik->i", d, np.linalg.inv(c), d))
    assert np.allclose(m.score(at), 1 / (1 + np.exp(log[0] - log[1])))


def test_kneser_ney_evidence():
    from collections import Counter

    plain = [b"the friend had a good day and the sun was out"] * 40
    toxic = [b"the idiot had a good day and the clown was out"] * 40
    words = (Counter(w for t in plain for w in T.tokens(t)), Counter(w for t in toxic for w in T.tokens(t)))
    m = T.count_models(words)
    assert m.word(b"idiot") > 1 > abs(m.word(b"day"))
    assert m.evidence(b"an idiot") > m.evidence(b"an idiot among many other words of the day") > abs(m.evidence(b"the day")) and m.evidence(b"") == 0.0


def by_hand(words, order, shared, discount=T.DISCOUNT):
    """p(class, history, letter), every count looked up anew in the spelt-out words."""
    runs = [[(T._BEGIN + w.decode() + T._END, c) for w, c in k.items()] for k in words]
    letters = {x for k in runs for s, _ in k for x in s[1:]}

    def count(k, g):
        who = runs[0] + runs[1] if k is None else runs[k]
        if len(g) == order or g[0] == T._BEGIN:
            return sum(c * sum(s.startswith(g, i) for i in range(len(s))) for s, c in who)
        return len({s[i - 1] for s, _ in who for i in range(1, len(s)) if s.startswith(g, i)})

    def p(k, h, x):
        if h is None:
            return 1 / (len(letters) + 1)
        if len(h) + 1 <= shared:
            k = None
        seen = [count(k, h + y) for y in letters]
        low = p(k, h[1:] if h else None, x)
        n = sum(seen)
        return max(count(k, h + x) - discount, 0) / n + discount * sum(c > 0 for c in seen) / n * low if n else low

    return p, letters


def test_kneser_ney_adds_up():
    """Both models' probabilities of the next letter, over all known letters and one unknown, sum to one; words are their letters' ratios."""
    import math
    from collections import Counter

    words = (Counter({b"aba": 3, b"ab": 2, b"ca": 1, b"abcab": 1}), Counter({b"bab": 2, b"caa": 4, b"cabba": 1}))
    for order, shared in ((5, 3), (4, 2), (3, 1)):
        m = T.count_models(words, order, shared)
        p, letters = by_hand(words, order, shared)
        for k in (0, 1):
            for h in ("", "a", T._BEGIN, "ab", T._BEGIN + "ca", "cab", "zz", "bab"[: order - 1], "caba"[: order - 1]):
                assert math.isclose(sum(p(k, h, x) for x in [*letters, "?"]), 1.0)
        for w in (b"aba", b"ab", b"cab", b"caa", b"z", b"abz", b"bcabab"):
            s = T._BEGIN + w.decode() + T._END
            want = sum(math.log(p(1, s[max(0, j + 1 - order) : j], s[j]) / p(0, s[max(0, j + 1 - order) : j], s[j])) for j in range(1, len(s)))
            assert math.isclose(m.word(w), want, rel_tol=1e-9, abs_tol=1e-9), (order, w)
    same = T.count_models((words[0], words[0]))
    assert all(abs(v) < 1e-12 for v in same.ratio.values()) and not same.leave


def test_repeated_ids_are_one_text(spark, labels):
    docs = spark.createDataFrame([(i, f"text {i} of words") for i in range(300)] + [(7, f"again {k}") for k in range(500)], "doc_id long, text string")
    marks = spark.createDataFrame([(i, i % 2) for i in range(300)] + [(7, 0)] * 50, "doc_id long, toxic int")
    a = {(r["doc_id"], r["score"]) for r in T.score(docs, marks).where("doc_id <> 7").collect()}
    assert len(a) == 299 and all(0 <= s <= 1 for _, s in a)
