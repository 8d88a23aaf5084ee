import os
import subprocess
import sys
from collections import Counter

import corpus_pipeline
from rowsketch.llm import quality_classifier
from rowsketch.shared import materialise


def test_stages(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    seen = [docs]
    for name, stage in corpus_pipeline.STAGES:
        seen.append(materialise(stage(spark, seen[-1], sf), name))
    base, good, lines, single, mixed, packed = seen
    assert all(x.columns == columns for x in seen[:-1])
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    want = {r["doc_id"] for r in quality_classifier.score(base, labels).where("predicted = 1").collect()}
    assert {r["doc_id"] for r in good.collect()} == want
    assert lines.count() == good.count() and lines.where("n_chars <> length(text)").count() == 0
    ids = [r["doc_id"] for r in single.collect()]
    assert len(ids) == len(set(ids)) and set(ids) <= want
    times = Counter(r["doc_id"] for r in mixed.collect())
    assert set(times) <= set(ids) and max(times.values()) <= 2
    assert {r["doc_id"] for r in packed.collect()} == set(times)


def test_repeated_rows_stay_in_the_mix(spark):
    """Line dedup empties the second copy of a row; the first copy must outlive that."""
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")

    def single(table):
        for _, stage in corpus_pipeline.STAGES[:3]:
            table = materialise(stage(spark, table, sf), "stage")
        return table.where("trim(text) <> ''")

    plain = {r["doc_id"] for r in single(docs).collect()}
    doubled = single(docs.unionByName(docs.where("doc_id % 2 = 0")))
    assert {r["doc_id"] for r in doubled.collect()} == plain and any(i % 2 == 0 for i in plain)
    taken = corpus_pipeline.pack(spark, corpus_pipeline.mix(spark, doubled, sf), sf)
    assert {r["doc_id"] for r in taken.collect()} == {r["doc_id"] for r in corpus_pipeline.mix(spark, doubled, sf).collect()}


def test_rest_works_without_the_operators(tmp_path):
    """The entry module imports without the subpackage and the pipeline."""
    root = os.path.dirname(os.path.abspath(corpus_pipeline.__file__))
    for name in os.listdir(root):
        if name not in ("corpus_pipeline.py", "rowsketch", ".git", "tests"):
            os.symlink(os.path.join(root, name), tmp_path / name)
    os.mkdir(tmp_path / "rowsketch")
    for name in os.listdir(os.path.join(root, "rowsketch")):
        if name != "llm":
            os.symlink(os.path.join(root, "rowsketch", name), tmp_path / "rowsketch" / name)
    code = "import __spark_entry__ as e; q = e.queries(); assert q and not any(k.startswith('op') or k == 'pipeline' for k in q); print(len(q))"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    done = subprocess.run([sys.executable, "-B", "-c", code], cwd=tmp_path, env=env, capture_output=True, text=True)
    assert done.returncode == 0, done.stderr
    os.mkdir(tmp_path / "tests")
    for name in os.listdir(os.path.join(root, "tests")):
        if name != "llm":
            os.symlink(os.path.join(root, "tests", name), tmp_path / "tests" / name)
    tests = [sys.executable, "-B", "-m", "pytest", "-q", "-p", "no:cacheprovider", "tests/test_kernel.py", "tests/test_entry.py::test_oracles_have_queries"]
    done = subprocess.run(tests, cwd=tmp_path, env=env, capture_output=True, text=True)
    assert done.returncode == 0, done.stdout
