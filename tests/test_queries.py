"""Every registered query with SQL gives the rows that DuckDB gives on the base tables."""

import pytest

from nestdep.queries import QUERIES, SQL

from .conftest import rows_of


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_matches_sql(spark, sf_dir, duck, name):
    got, want = QUERIES[name](spark, sf_dir).toPandas(), duck.sql(SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows_of(got) == rows_of(want)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(SQL) - {"w_inclusion_runtime", "w_inclusion_scale", "w_functional_scale", "w_complexity_sweep"}))
def test_query_without_sql_runs(spark, sf_dir, name):
    rows = QUERIES[name](spark, sf_dir).collect()
    assert rows and any(any(v is not None for v in r) for r in rows)


def test_entry_and_names():
    import __spark_entry__ as entry

    assert set(SQL) <= set(entry.queries()) and set(entry.oracle_sql()) <= set(entry.queries())


def test_blowup_and_runtime_take_whole_collections(spark, sf_dir, monkeypatch):
    from nestdep import workloads
    from nestdep.operators import results
    from nestdep.sources.collections import build_collection

    whole = build_collection("product_docs", spark, sf_dir)
    assert QUERIES["w_blowup"](spark, sf_dir).collect() == results.blowup(whole).collect()
    assert QUERIES["w_blowup"](spark, sf_dir).collect() != results.blowup(build_collection("product_docs", spark, sf_dir, cap=10)).collect()
    timed = []
    monkeypatch.setattr(results, "time_run", lambda make, repeat=3, limit_s=None: timed.append(repeat) or {"status": "ok", "seconds": 1.0})
    rows = QUERIES["w_inclusion_runtime"](spark, sf_dir).collect()
    related = whole.select(*[p.split(".")[1].split("[")[0] for p in ("$.partkey", "$.brand", "$.related", "$.suppliers[*]")])
    assert {r["expansion"] for r in rows if r["collection"] == "product_docs"} == {float(workloads.expansion_factor(related).first()["expansion"])}
    assert {r["collection"] for r in rows} == {"order_docs", "customer_docs", "product_docs", "product_docs cap 10"} and set(timed[1:]) == {3}
