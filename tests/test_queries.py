"""Every query with an SQL twin gives the twin's rows; every other one runs and has rows."""

import inspect

import pytest

from cutstream import catalog, workloads
from tests.helpers import rows_of, rows_of_sql

ORACLES = catalog.oracles()
QUERIES = catalog.queries()
LIGHT = [n for n in QUERIES if not n.startswith("w")]


@pytest.mark.parametrize("name", [n for n in LIGHT if n in ORACLES])
def test_sql_twin(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    cols, expected = rows_of_sql(duck, ORACLES[name])
    assert sorted(df.columns) == cols
    assert rows_of(df) == expected


@pytest.mark.parametrize("name", [n for n in LIGHT if n not in ORACLES])
def test_runs(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0


@pytest.mark.parametrize("name", ["w04_model_kind", "w10_offline_yardstick"])
def test_workload(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0


def test_memory_is_measured_and_smaller_buffers_have_smaller_models(spark, sf):
    rows = workloads.memory(spark, sf).collect()
    assert [r.alg for r in rows] == ["bmp", "bmp", "pgg", "cdg"] and all(r.peak_bytes > 0 for r in rows)
    assert rows[0].delta > rows[1].delta and rows[0].model_bytes > rows[1].model_bytes


def test_fewer_messages_and_more_local_rows_than_by_hash(spark, sf, duck):
    hashed, buffered = workloads.application(spark, sf).collect()
    assert hashed.two_hop > buffered.two_hop and hashed.one_hop > buffered.one_hop
    assert hashed.rows_local < buffered.rows_local
    lines = duck.sql("SELECT count(*) FROM lineitem").fetchall()[0][0]
    assert hashed.rows_stored == buffered.rows_stored == lines


def test_more_refinement_does_not_lose(spark, sf):
    rows = {r.rounds: r for r in workloads.refinement_rounds(spark, sf).collect()}
    assert set(rows) == {"1", "5", "25"} and all(r.feasible for r in rows.values())
    assert rows["25"].geomean_cut <= 1.02 * rows["1"].geomean_cut


def test_whole_grids_name_parameters():
    for name, grid in workloads.FULL.items():
        assert set(grid) <= set(inspect.signature(getattr(workloads, name)).parameters)


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 8


def test_lines_of_many_documents_stay_linked(spark, tmp_path):
    from cutstream.sources import graphs

    line = "a line that thirty documents have"
    spark.createDataFrame([(i, f"{line}\nown words {i}") for i in range(30)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = sorted((r.src, r.dst) for r in graphs.edges(spark, str(tmp_path), "docline_star").collect())
    assert got == [(0, i) for i in range(1, 30)]
    assert graphs.edges(spark, str(tmp_path), "docline").count() == 0  # its twin has the cap too
