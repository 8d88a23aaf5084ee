"""Queries whose job once ran on made-up rows read a given table, and agree with their SQL."""

import pytest

import __spark_entry__ as entry
from rowsketch.plans import queries

#: query: the table that Spark reads for it
READS = {
    "scaling_checks": "embeddings",
    "scaling_report": "embeddings",
    "shrink_trace": "embeddings",
    "primitive_values": "lineitem",
    "pair_constants": "embeddings",
    "latency_checks": "embeddings",
    "latency_report": "embeddings",
    "hard_instances": "events",
    "hard_instance_cert": "embeddings",
    "guarantee_curves": "events",
}


@pytest.mark.parametrize("name", READS)
def test_reads_its_table(spark, sf, monkeypatch, name):
    seen, load = [], queries.load
    monkeypatch.setattr(queries, "load", lambda s, d, table, *a, **k: seen.append(table) or load(s, d, table, *a, **k))
    monkeypatch.setattr(queries, "_MADE", {})
    df = queries.QUERIES[name](spark, sf)
    got = df.collect()
    assert READS[name] in seen and got
    sql = entry.oracle_sql().get(name)
    if sql is None:
        return
    import duckdb

    c = duckdb.connect()
    for t in set(seen):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    r = c.execute(sql)
    names = [d[0] for d in r.description]
    plain = lambda row: tuple(round(x, 6) + 0.0 if isinstance(x, float) else x for x in row)
    assert sorted(plain(r[n] for n in names) for r in got) == sorted(map(plain, r.fetchall()))
