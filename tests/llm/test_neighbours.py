import numpy as np
import pytest

from rowsketch.llm import neighbours as N


@pytest.fixture(scope="module")
def table(spark):
    return spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")


def test_hilbert_is_a_walk():
    """Neighbours along the curve are neighbours in the grid, and every cell comes once."""
    for d, bits in ((2, 4), (3, 3)):
        side = 1 << bits
        cells = np.stack(np.meshgrid(*[np.arange(side)] * d, indexing="ij"), -1).reshape(-1, d)
        key = N.hilbert(cells, bits)
        assert sorted(key) == list(range(side**d))
        steps = np.abs(np.diff(cells[np.argsort(key)], axis=0)).sum(axis=1)
        assert (steps == 1).all()


def test_recall(spark, table):
    p = table.toPandas()
    want = N.brute_force(p.vec_id.to_numpy(), np.array(p.embedding.tolist(), np.float64))
    got = N.search(table).toPandas()
    assert set(got.query_id) == set(want) and (got.groupby("query_id")["rank"].max() == 20).all()
    hits = total = 0
    for q, g in got.groupby("query_id"):
        score = dict(want[q])
        hits += sum(v in score for v in g.vec_id)
        total += 20
        for v, s in zip(g.vec_id, g.score):
            assert v not in score or abs(s - score[v]) < 1e-12
        assert (np.diff(g.sort_values("rank").score) <= 0).all()
    assert hits / total >= 0.9


def test_copies_and_odd_rows(spark):
    rng = np.random.default_rng(1)
    unit = lambda v: (v / np.linalg.norm(v)).tolist()
    hot = unit(rng.standard_normal(8))
    rows = [(k, hot) for k in range(0, 400, 2)] + [(k, unit(rng.standard_normal(8))) for k in range(401, 460)]
    rows += [(1000, None), (1001, [0.0] * 8), (1002, [float("nan")] * 8), (1003, [1.0]), (1004, [None] * 8), (None, hot), (1005, [float("inf")] + [1.0] * 7), (0, hot)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = N.search(df, curves=4).toPandas()
    assert set(got.query_id) == set(range(0, 400, 20)) | {420, 440}
    first = got[got.query_id == 40].sort_values("rank").vec_id.tolist()
    assert first == [k for k in range(0, 44, 2) if k != 40][:20]
    assert not set(got.vec_id) & {1000, 1001, 1002, 1003, 1004, 1005}


def test_few_rows(spark):
    df = spark.createDataFrame([(20, [1.0, 0.0]), (21, [0.0, 1.0]), (22, [1.0, 1.0])], "vec_id long, embedding array<double>")
    got = N.search(df).orderBy("rank").collect()
    assert [(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in got] == [(20, 1, 22, 1.0), (20, 2, 21, 0.0)]
    assert N.search(df.where("false")).count() == 0


def test_ties_between_different_vectors_go_to_smaller_ids(spark):
    """Hundreds of distinct vectors with one and the same product with the query."""
    rng = np.random.default_rng(3)
    rows = [(20, [1.0, 0.0, 0.0])]
    rows += [(600 + k, [1.0, float(a), float(b)]) for k, (a, b) in enumerate(rng.permutation([(i, j) for i in range(-10, 10) for j in range(1, 21)]))]
    rows += [(2001 + 2 * k, [0.5, float(k % 7), float(k % 11)]) for k in range(300)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = N.search(df).where("query_id = 20").orderBy("rank").collect()
    assert [(r["vec_id"], r["score"]) for r in got] == [(600 + k, 1.0) for k in range(20)]
    ids, x = np.array([r[0] for r in rows]), np.array([r[1] for r in rows])
    want = N.brute_force(ids, x)
    for q, g in N.search(df).toPandas().groupby("query_id"):
        assert [(v, s) for v, s in g.sort_values("rank")[["vec_id", "score"]].itertuples(index=False)] == want[q]


def test_a_code_is_off_by_its_slack_at_most():
    rng = np.random.default_rng(4)
    x, y = rng.standard_normal((500, 24)) * rng.lognormal(0, 3, (500, 1)), rng.standard_normal((40, 24))
    code, step = N.codes(x)
    got = (y.astype(np.float32) @ code.astype(np.float32).T).astype(np.float64) * step
    assert (np.abs(got - y @ x.T) <= N.slack_of(step[None, :], np.linalg.norm(y, axis=1)[:, None], 24)).all()


def test_a_share_of_the_rows_is_met(spark):
    """Recall and products at several sizes; the share met falls as tables grow."""
    shares = []
    for n in (4000, 16_000):
        rng = np.random.default_rng(n)
        x = rng.standard_normal((n, 16))
        x /= np.linalg.norm(x, axis=1)[:, None]
        points = spark.createDataFrame([(i, [i], v.tolist()) for i, v in enumerate(x)], "rep long, ids array<long>, v array<double>").cache()
        asking = points.where("rep % 100 = 0").select("rep")
        met = N.candidates(points, asking, curves=24).toPandas()
        hits = 0
        for r, near in zip(met.rep, met.near):
            s = x @ x[r]
            s[r] = -9
            hits += len(set(np.argsort(-s)[:20]) & set(near))
        assert hits / 20 / len(met) >= 0.9
        shares.append(met.met.mean() / n)
    assert shares[1] < 0.8 * shares[0] < 0.8


def test_a_vector_that_is_near_to_all(spark):
    rng = np.random.default_rng(8)
    rows = [(1, [50.0] + [0.0] * 7)] + [(20 * k, [float(abs(v[0]) + 1), *map(float, v[1:])]) for k, v in enumerate(rng.standard_normal((400, 8)), 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    first = N.search(df).where("rank = 1").collect()
    assert len(first) == 400 and all(r["vec_id"] == 1 for r in first)
