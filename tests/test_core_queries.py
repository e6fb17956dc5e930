"""Every query with a DuckDB twin agrees with it on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry
from steepdraw import registry
from steepdraw.sources.tables import TABLES


def text(v):
    if isinstance(v, float):
        return repr(round(v, 6) + 0.0)
    return "[" + ",".join(map(text, v)) + "]" if isinstance(v, list | tuple) else repr(v)


@pytest.fixture(scope="module")
def duck(tiny):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_twin(spark, tiny, duck, name):
    df = registry.queries()[name](spark, tiny)
    cols = sorted(df.columns)
    got = sorted("|".join(text(r[c]) for c in cols) for r in df.collect())
    out = duck.execute(registry.oracle_sql()[name])
    names = [c[0] for c in out.description]
    assert sorted(names) == cols
    want = sorted("|".join(text(r[names.index(c)]) for c in cols) for r in out.fetchall())
    assert got == want


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_filters_and_columns_reach_the_scan(spark, tiny):
    plan = registry.queries()["filter_predicates"](spark, tiny)._jdf.queryExecution().toString()
    assert "PushedFilters: [" in plan and "l_tax" not in plan.split("ReadSchema")[-1]


@pytest.mark.parametrize("name", ["train_history_trace", "train_staged_trace", "train_identical_trace", "distributed_modes", "staging_ablation"])
def test_traces_run(spark, tiny, name):
    assert registry.queries()[name](spark, tiny).count() > 0


def test_recursion_starts_from_a_table(spark, tiny):
    rows = registry.queries()["cte_recursive"](spark, tiny).where("k = 12").collect()
    goal = {r[0]: r[1] for r in spark.read.parquet(f"{tiny}/lineitem.parquet").groupBy("l_returnflag").avg("l_discount").collect()}
    assert {r.l_returnflag: r.w for r in rows} == {f: pytest.approx(g * (1 - 0.5**11), abs=1e-9) for f, g in goal.items()}


def test_minibatch_uniforms_are_drawn_for_rows_of_a_table(spark, tiny):
    df = registry.queries()["udtf_draw_minibatch"](spark, tiny)
    assert df.inputFiles() and df.count() == 64 * spark.read.parquet(f"{tiny}/supplier.parquet").count()


def test_length_costs_are_timed_on_all_rows_of_a_table(spark, tiny):
    df = registry.queries()["length_cost_timed"](spark, tiny)
    rows = df.collect()
    assert df.inputFiles() and sorted((r.outputs, r.inputs) for r in rows) == [(10, 64), (32, 64), (128, 128), (256, 512)]
    assert {r.rows for r in rows} == {spark.read.parquet(f"{tiny}/embeddings.parquet").count()} and all(r.timed > 0 for r in rows)
