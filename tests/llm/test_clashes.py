"""Input columns named like anything that an operator makes on its way, or with names that need quoting."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from rowsketch.llm import language_model, line_dedup, mixing, neighbours, packing, pseudonyms, quality_classifier, quality_rules, simhash, toxicity
from rowsketch.llm.queries import tokenizer_path

NAMES = ("_ld_id _ld_row _ld_gone dedup_id dedup_row dedup_gone dedup_key dedup_copy _copy _key _id _gone _text_bytes statistics x y doc s t h k n r m g other shift salt run words "
         "node root mark least fp text_key mask key a b component_id size _u _w _whole _rank _fine _coarse _below _cut _scale _copies _doc target taken source_size "
         "held_out score predicted curve rep ids asks near met curve_id range block kind body v shard outs sizes text_2 count n_words kept value pos col").split()  # fmt: skip


@pytest.fixture(scope="module")
def base(make):
    line = "one line with more than ten words in it to be sure of it"
    return make([(k, f"text number {k} says the thing\n{line}" if k % 2 else f"a wholly other text of number {k} and of no other", f"s{k % 3}") for k in range(60)] + [(2, None), (3, "x"), (3, "x")])


@pytest.fixture(scope="module")
def wide(base):
    return base.select("*", *[F.lit(f"<{c}>").alias(c) for c in NAMES], F.lit(1).alias("a.b"), F.lit(2).alias("c `d"))


def rows(df, columns):
    return sorted(tuple(str(v) for v in r) for r in df.select(*columns).collect())


OPERATORS = {
    "packing": lambda d, l: packing.pack_documents(d, tokenizer_path()).select("doc_id", "length", "ids_crc32"),
    "pseudonyms": lambda d, l: pseudonyms.pseudonymise(d).select("doc_id", "text", "n_email"),
    "toxicity": toxicity.score,
    "line_dedup": lambda d, l: line_dedup.dedup_lines(d).select("doc_id", "text"),
    "line_dedup_counted": lambda d, l: line_dedup.dedup_lines(d, count="count").select("doc_id", "text", "count"),
    "quality": quality_classifier.score,
    "language_model": lambda d, l: language_model.score(d).select("doc_id", "n_tokens", "n_known", F.round("score", 6).alias("z")),
    "simhash": lambda d, l: simhash.near_duplicates(d),
    "rules": lambda d, l: quality_rules.apply_rules(d).select("doc_id", "n_words", "kept"),
    "mix_report": lambda d, l: mixing.mix_report(d, weight=mixing.length_odds()),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_operator(name, base, wide, labels):
    want, got = OPERATORS[name](base, labels), OPERATORS[name](wide, labels)
    assert got.columns == want.columns and rows(got, want.columns) == rows(want, want.columns)


PASSING = {
    "line_dedup": lambda d, l: line_dedup.dedup_lines(d),
    "keep_good": lambda d, l: quality_classifier.keep_good(d, l),
    "keep_first": lambda d, l: simhash.keep_first(d),
    "keep_similar": lambda d, l: simhash.keep_similar(d),
    "mix": lambda d, l: mixing.mix(d, weight=mixing.length_odds()),
    "pseudonyms": lambda d, l: pseudonyms.pseudonymise(d).drop(*[f"n_{k}" for k in pseudonyms.KINDS]),
}


@pytest.mark.parametrize("name", PASSING)
def test_other_columns_pass_through(name, base, wide, labels):
    want, got = PASSING[name](base, labels), PASSING[name](wide, labels)
    assert got.columns == wide.columns and rows(got, base.columns) == rows(want, base.columns)
    one = got.first().asDict()
    assert all(one[c] == f"<{c}>" for c in NAMES) and one["a.b"] == 1 and one["c `d"] == 2


def test_stages(spark, wide):
    docs = wide.where("doc_id is not null")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, "/root/testdata/sf0.01")
        assert docs.columns == wide.columns
    assert corpus_pipeline.STAGES[-1][1](spark, docs, "/root/testdata/sf0.01").count() >= 0


def test_neighbours(spark):
    plain = spark.createDataFrame([(k, [float(k % 7), float(k % 5), 1.0]) for k in range(100)], "vec_id long, embedding array<double>")
    clashing = plain.select("*", *[F.lit(1).alias(c) for c in ("id", "v", "rep", "ids", "asks", "curve", "range", "block", "score", "rank", "query_id", "near", "salt", "r", "n")])
    columns = ["query_id", "rank", "vec_id", "score"]
    assert rows(neighbours.search(clashing), columns) == rows(neighbours.search(plain), columns)
