import pytest
from pyspark.sql import functions as F

from rowsketch.llm import mixing, quality_rules


def duck(query, pairs):
    import duckdb
    import pandas as pd

    c = duckdb.connect()
    frame = pd.DataFrame(pairs, columns=["doc_id", "text", "source"])  # noqa: F841
    c.execute("CREATE TABLE documents AS SELECT doc_id::BIGINT AS doc_id, text::VARCHAR AS text, source::VARCHAR AS source FROM frame")
    r = c.execute(query)
    names = [d[0] for d in r.description]
    return sorted((tuple(str(x) for x in row) for row in r.fetchall())), names


def plain_repeats(text):
    import re

    w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    spots = {}
    for i in range(len(w) - 4):
        spots.setdefault(tuple(w[i : i + 5]), []).append(i)
    return len({j for s in spots.values() if len(s) > 1 for i in s for j in range(i, i + 5)})


PAIRS = [(1, "a b c d e f a b c d e", "s"), (2, None, None), (3, "", "s"), (4, "x\nx\n\nx y\nx", "t"), (5, "one two three four five " * 4, "t"), (6, "the " * 12, "u"), (6, "the " * 12, "u"), (None, "of the and to in is that it for on with", None), (7, "# * $ % & | < >", "u"), (8, "The " + "word " * 3 + "\n- b\n* c\n" * 3, "v")]


def test_rules_match_duckdb_and_plain(make, spark):
    df = make(PAIRS)
    columns = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]
    got = quality_rules.apply_rules(df).select(*columns).collect()
    want, names = duck(quality_rules.oracle(), PAIRS)
    assert names == columns
    assert sorted(tuple(str(x) for x in r) for r in got) == want
    by_text = {r["text"]: r["n_repeat_words"] for r in quality_rules.apply_rules(df).collect()}
    for _, t, _ in PAIRS:
        assert by_text[t] == plain_repeats(t)


def test_rules_odd(odd, none, documents):
    assert quality_rules.apply_rules(odd).count() == odd.count()
    assert quality_rules.apply_rules(none).count() == 0
    clash = odd.withColumn("kept", F.lit("x")).withColumn("n_words", F.lit("y"))
    assert dict(quality_rules.apply_rules(clash).dtypes)["kept"] == "boolean"
    plan = quality_rules.apply_rules(documents)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Exchange" not in plan


def test_mix_matches_duckdb(make):
    pairs = [(i, "w " * (i % 7), None if i % 11 == 0 else f"s{i % 5}") for i in range(300)] + [(12, "w " * 5, "s2"), (None, "w w", "s1"), (400, None, "s3")]
    got = mixing.mix_report(make(pairs)).select("doc_id", "size", "source_size", F.round("target", 3).alias("target"), "taken").collect()
    want, _ = duck(mixing.oracle(), pairs)
    assert sorted(tuple(str(x) for x in r) for r in got) == want


def test_mix_keeps_its_promises(make):
    pairs = [(i, "w " * (1 + i % 9), f"s{0 if i % 3 else i % 4}") for i in range(3000)]
    r = mixing.mix_report(make(pairs)).toPandas()
    total = r["size"].sum()
    per = r.groupby("source").agg(target=("target", "first"), taken=("taken", "sum"), size=("source_size", "first"))
    assert abs(per.target.sum() - 1.5 * total) < 1e-6 and (per.target <= 2 * per["size"] + 1e-9).all()
    assert (abs(per.taken - per.target) <= 9).all() and (r.taken <= 2 * r["size"]).all()
    again = mixing.mix_report(make(pairs[::-1])).toPandas()
    assert r.set_index("doc_id").taken.sort_index().equals(again.set_index("doc_id").taken.sort_index())
    copies = mixing.mix(make(pairs)).groupBy("doc_id").count().toPandas().set_index("doc_id")["count"]
    taken, size = r.set_index("doc_id").taken, r.set_index("doc_id")["size"]
    assert (copies.reindex(taken.index, fill_value=0) * size == taken).all()


def test_mix_weights_change_the_odds(make, spark):
    df = make([(i, "w w w", "a") for i in range(2000)] + [(10_000 + i, "w w w", "b") for i in range(1000)]).withColumn("like", F.when(F.col("doc_id") % 2 == 0, 3.0).otherwise(1.0))
    r = mixing.mix_report(df, weight="like").toPandas()
    a = r[r.source == "b"]
    assert a[a.doc_id % 2 == 0].taken.sum() > a[a.doc_id % 2 == 1].taken.sum()


def test_mix_odd(odd, none):
    assert mixing.mix_report(odd).count() == odd.count() and mixing.mix(odd).columns == odd.columns
    assert mixing.mix_report(none).count() == 0


@pytest.mark.parametrize("sizes", [[100, 1, 1], [1, 1, 1, 1], [5, 0, 7], [10]])
def test_targets_by_repeated_sharing(spark, sizes):
    names = [f"s{k}" for k in range(len(sizes))]
    got = {r["source"]: r["target"] for r in mixing.targets(spark.createDataFrame(list(zip(names, sizes)), "source string, source_size long")).collect()}
    w = [(3, 1, 2)[k % 3] for k in range(len(sizes))]
    left, open_, out = 1.5 * sum(sizes), set(range(len(sizes))), [0.0] * len(sizes)
    while open_:
        share = sum(w[k] for k in open_)
        over = {k for k in open_ if left * w[k] / share > 2 * sizes[k]}
        if not over:
            for k in open_:
                out[k] = left * w[k] / share
            break
        for k in over:
            out[k] = 2.0 * sizes[k]
        left -= sum(out[k] for k in over)
        open_ -= over
    assert all(abs(got[n] - t) < 1e-9 for n, t in zip(names, out))


def test_odds_match_duckdb(make):
    """Long texts are likelier; sources that are short of them, full of them, at their cap, and below their size."""
    import random

    rng = random.Random(2)
    pairs = [(i, "w " * rng.choice([0, 3, 50, 99, 100, 150, 999, 1000, 1500]), rng.choice(["a", "a", "a", "a", "b", "c", None])) for i in range(900)]
    pairs += [(2000 + i, "w " * 120, "d") for i in range(3)] + [(3000, "", "e"), (12, "w " * 1200, "a")]
    df = make(pairs)
    got = mixing.mix_report(df, weight=mixing.length_odds()).select("doc_id", "size", "source_size", F.round("target", 3).alias("target"), "taken").collect()
    want, _ = duck(mixing.oracle(), pairs)
    assert sorted(tuple(str(x) for x in r) for r in got) == want
    r = mixing.mix_report(df, weight=mixing.length_odds()).toPandas()
    per = r.groupby("source", dropna=False).agg(target=("target", "first"), taken=("taken", "sum"))
    assert (abs(per.taken - per.target) <= 1500).all() and (r.taken <= 2 * r["size"]).all()
    short = r[(r.source == "a") & (r["size"].between(1, 99))]
    long = r[(r.source == "a") & (r["size"] >= 1000)]
    assert (long.taken / long["size"]).mean() > 1.3 * (short.taken / short["size"]).mean()


def test_any_positive_odds(make):
    df = make([(i, "w " * (1 + i % 5), f"s{i % 3}") for i in range(3000)]).withColumn("like", F.when(F.col("doc_id") % 10 == 0, F.lit(None)).otherwise(F.exp(F.rand(3) * 12 - 6)))
    r = mixing.mix_report(df, weight="like").toPandas()
    per = r.groupby("source").agg(target=("target", "first"), taken=("taken", "sum"))
    assert (abs(per.taken - per.target) <= 5).all() and (r.taken <= 2 * r["size"]).all()
