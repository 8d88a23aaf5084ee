"""Toxicity by class-conditional Kneser-Ney language models.

Two Kneser-Ney models, one of toxic and one of ordinary texts, give each word a
log-likelihood letter by letter: an expression is a run of letters inside a
word, from its beginning mark to its end mark.  The longest runs are counted
as they occur; every shorter one by the number of different letters that come
before it (a run at the beginning of a word has none, and counts as it occurs).
From ``shared`` letters down the classes share these continuation counts, so a
rare expression that neither class knows well falls back to what both know,
and weighs almost nothing.  (Words alone do not do: a class may mark its words
by how they begin, in spellings that training never saw whole.)

A toxic text is mostly ordinary words: each of its words comes from the toxic
model with probability ``mix`` and from the ordinary one otherwise.  A text's
evidence is its log-likelihood as a toxic text less that as an ordinary text,
over its length.  A logistic curve, fitted on labelled texts that the counts
have not seen, turns it into a score at which ``threshold`` is the best cut.

Fitting reads at most ``sample_texts`` labelled ids of each class, those with
the least hash, and one whole text of each (of an id with several texts, the
one with the least hash); the bound is a parameter.  Scoring covers every whole
text.  Labels, language, source and id are never inputs of a score.

Null and empty texts carry no evidence and get the curve's value at zero;
labels that are null or neither 0 nor 1 are passed over; an id with both labels
has label 1; without texts of both classes the score is the share of label 1
(0 if none); an empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowsketch.llm.common import fold_of, text_bytes
from rowsketch.shared import materialise

FOLDS = 4
HELD_OUT = 2
THRESHOLD = 0.3
#: Labelled texts of each class that are read for fitting, at most.
SAMPLE_TEXTS = 2_500
#: Of these, the share kept from the counts to fit the curve.
CURVE_SHARE = 0.3
#: Discount of seen counts.
DISCOUNT = 0.75
#: Letters of the longest expression, and of the longest one whose counts the classes share.
ORDER = 5
SHARED = 3
#: Share of a toxic text's words that the toxic model writes, and words added to every text's length.
MIX = 0.01
PADDING = 20
#: Words whose evidence a Python worker remembers.
CACHE_WORDS = 400_000
_STRIP = b".,;:!?\"'()[]{}#*$%&|<>"
_BEGIN, _END = "\x01", "\x02"


def tokens(text: bytes) -> list[bytes]:
    """Lower-cased words without the symbols around them."""
    return [w for w in (x.strip(_STRIP) for x in text.lower().split()) if w]


@dataclass
class KneserNey:
    """Toxic against ordinary: log ratios of seen expressions, and of leaving a history by its backoff."""

    ratio: dict[str, float] = field(default_factory=dict)
    leave: dict[str, float] = field(default_factory=dict)
    order: int = ORDER
    shared: int = SHARED
    slope: float = 0.0
    offset: float = 0.0
    cache: dict[bytes, float] = field(default_factory=dict, repr=False)

    def word(self, w: bytes) -> float:
        """Log-likelihood difference of a word."""
        s = _BEGIN + w.decode("utf-8", "replace") + _END
        total = 0.0
        for j in range(1, len(s)):
            g = s[max(0, j + 1 - self.order) : j + 1]
            while len(g) > self.shared:
                seen = self.ratio.get(g)
                if seen is not None:
                    total += seen
                    break
                total += self.leave.get(g[:-1], 0.0)
                g = g[1:]
        return total

    def evidence(self, text: bytes) -> float:
        """Log-likelihood as a toxic text less that as an ordinary one, over the length."""
        w = tokens(text)
        cache = self.cache
        if len(cache) > CACHE_WORDS:
            cache.clear()
        for x in set(w).difference(cache):
            # log((1 - mix) + mix * p_toxic / p_ordinary)
            cache[x] = float(np.logaddexp(np.log1p(-MIX), np.log(MIX) + self.word(x)))
        return sum(map(cache.__getitem__, w)) / (len(w) + PADDING)

    def score(self, evidence: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.slope * evidence + self.offset, -500, 500)))


def _continuations(grams: list[list[Counter]], n: int, classes: tuple[int, ...], order: int) -> Counter:
    """Counts of expressions of ``n`` letters over some classes: occurrences at full length and at the beginning of a word, else the different letters before them."""
    out: Counter = Counter()
    for k in classes:
        for g, c in grams[k][n].items():
            if n == order or g[0] == _BEGIN:
                out[g] += c
    if n < order:
        for g in set().union(*[grams[k][n + 1] for k in classes]):
            out[g[1:]] += 1
    return out


def count_models(words: tuple[Counter, Counter], order: int = ORDER, shared: int = SHARED, discount: float = DISCOUNT) -> KneserNey:
    """From counts of words in ordinary (0) and toxic (1) texts."""
    grams = [[Counter() for _ in range(order + 1)] for _ in (0, 1)]
    for k in (0, 1):
        for w, c in words[k].items():
            s = _BEGIN + w.decode("utf-8", "replace") + _END
            for j in range(1, len(s)):
                for n in range(1, min(order, j + 1) + 1):
                    grams[k][n][s[j - n + 1 : j + 1]] += c
    #: Of class 0, class 1 and both.
    tables: list[dict[int, Counter]] = [{n: _continuations(grams, n, (k,), order) for n in range(shared + 1, order + 1)} for k in (0, 1)]
    tables.append({n: _continuations(grams, n, (0, 1), order) for n in range(1, shared + 1)})
    total: list[Counter] = [Counter(), Counter(), Counter()]
    types: list[Counter] = [Counter(), Counter(), Counter()]
    for k, levels in enumerate(tables):
        for level in levels.values():
            for g, c in level.items():
                total[k][g[:-1]] += c
                types[k][g[:-1]] += 1
    letters = len({g[-1] for t in grams for g in t[1]}) + 1
    memo: dict[tuple[int, str], float] = {}

    def p(k: int, g: str) -> float:
        if not g:
            return 1.0 / letters
        k = k if len(g) > shared else 2
        got = memo.get((k, g))
        if got is None:
            h = g[:-1]
            low = p(k, g[1:])
            n = total[k][h]
            got = memo[k, g] = max(tables[k][len(g)][g] - discount, 0.0) / n + discount * types[k][h] / n * low if n else low
        return got

    model = KneserNey(order=order, shared=shared)
    weight = lambda k, h: discount * types[k][h] / total[k][h] if total[k][h] else 1.0
    for n in range(shared + 1, order + 1):
        for g in set(tables[0][n]) | set(tables[1][n]):
            model.ratio[g] = float(np.log(p(1, g) / p(0, g)))
    for h in set(total[0]) | set(total[1]):
        a, b = weight(1, h), weight(0, h)
        if a != b:
            model.leave[h] = float(np.log(a / b))
    return model


def fit_curve(evidence: np.ndarray, y: np.ndarray, weight: np.ndarray, threshold: float) -> tuple[float, float]:
    """Slope and offset of a logistic curve whose value is ``threshold`` at the cut with the best F1."""
    spread = evidence.std() or 1.0
    z = evidence / spread
    a, b = 1.0, 0.0
    for _ in range(50):  # Newton steps with a small ridge
        p = 1 / (1 + np.exp(-np.clip(a * z + b, -30, 30)))
        g = np.array([((p - y) * z * weight).sum() + 1e-3 * a, ((p - y) * weight).sum()])
        w = p * (1 - p) * weight
        h = np.array([[(w * z * z).sum() + 1e-3, (w * z).sum()], [(w * z).sum(), w.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        a, b = a - step[0], b - step[1]
        if abs(step).max() < 1e-8:
            break
    a = max(a, 1e-3)
    order = np.argsort(-z)
    hit = np.cumsum(weight[order] * y[order])
    f1 = 2 * hit / (np.cumsum(weight[order]) + (weight * y).sum())
    k = int(np.argmax(f1))
    cut = (z[order[k]] + (z[order[k + 1]] if k + 1 < len(z) else z[order[k]])) / 2
    return a / spread, float(np.log(threshold / (1 - threshold)) - a * cut)


def fit(docs: DataFrame, labels: DataFrame, *, label: str = "toxic", folds: int = FOLDS, held_out: int = HELD_OUT, sample_texts: int = SAMPLE_TEXTS, threshold: float = THRESHOLD, doc_id: str = "doc_id", text: str = "text") -> KneserNey:
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where("y in (0, 1)").where(fold_of(F.col("doc_id"), folds) != held_out)
    marks = marks.where("doc_id is not null").groupBy("doc_id").agg(F.max("y").alias("y"))
    shares = {r["y"]: r["n"] for r in marks.groupBy("y").agg(F.count("*").alias("n")).collect()}
    model = KneserNey()
    if len(shares) < 2:
        model.offset = -50.0 if not shares.get(1) else 50.0
        return model
    order = F.xxhash64("doc_id")
    chosen = None
    for y in (0, 1):  # a bounded number of ids of each class
        part = marks.where(F.col("y") == y).orderBy(order, "doc_id").limit(sample_texts)
        chosen = part if chosen is None else chosen.unionByName(part)
    ids = [(r["doc_id"], r["y"]) for r in chosen.collect()]
    few = docs.sparkSession.createDataFrame(ids, "doc_id long, y int")
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), text_bytes(text).alias("text")).join(F.broadcast(few), "doc_id").groupBy("doc_id", "y").agg(F.min_by("text", F.xxhash64("text")).alias("text"))
    rows = rows.select("y", (F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(1000)) < int(1000 * CURVE_SHARE)).alias("curve"), "text")
    words, later = (Counter(), Counter()), []
    # written in parallel, then read a few files at a time: the driver holds one part of the sample
    for r in materialise(rows, "sample").coalesce(8).toLocalIterator():
        if r["curve"]:
            later.append((r["y"], bytes(r["text"])))
        else:
            words[r["y"]].update(tokens(bytes(r["text"])))
    if not words[0] or not words[1] or len({y for y, _ in later}) < 2:
        model.offset = float(np.log(shares[1] / shares[0]))
        return model
    model = count_models(words)
    y = np.array([k for k, _ in later])
    # the sample holds the classes in other proportions than the labels do
    weight = np.array([shares[k] / max(1, (y == k).sum()) for k in y])
    model.slope, model.offset = fit_curve(np.array([model.evidence(t) for _, t in later]), y, weight / weight.sum() * len(y), threshold)
    return model


def score(docs: DataFrame, labels: DataFrame, *, label: str = "toxic", folds: int = FOLDS, held_out: int = HELD_OUT, threshold: float = THRESHOLD, sample_texts: int = SAMPLE_TEXTS, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, held_out, score, predicted) for every document."""
    import pickle

    model = fit(docs, labels, label=label, folds=folds, held_out=held_out, sample_texts=sample_texts, threshold=threshold, doc_id=doc_id, text=text)
    model.cache.clear()
    # as large as the sample's bound lets it be
    sent = docs.sparkSession.sparkContext.broadcast(pickle.dumps(model))
    held: dict[str, KneserNey] = {}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pickle

        m = held.get("model") or held.setdefault("model", pickle.loads(sent.value))
        for rb in batches:
            e = np.fromiter((m.evidence(t.as_buffer().to_pybytes()) for t in rb.column(1)), np.float64, rb.num_rows)
            yield pa.RecordBatch.from_arrays([rb.column(0), pa.array(m.score(e))], ["doc_id", "score"])

    scored = docs.select(F.col(doc_id).cast("long").alias("doc_id"), text_bytes(text).alias("text")).mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", (fold_of(F.col("doc_id"), folds) == held_out).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
