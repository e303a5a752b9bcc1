"""The registry: names, shapes, independence of the pipeline operators, and SQL for small queries."""

import importlib.util
import subprocess
import sys

import duckdb
import pytest

import __spark_entry__ as e

SF = "/root/testdata/sf0.001"
SMALL = ["token_counts", "batches_fixed", "cells_count", "cost_surface", "optimum_integer", "offers_block", "offers_adaptive", "contradiction_block", "offers_noisy", "offers_usage", "clusters_embedding", "semantic_filter_quality", "price_statement", "batches_packed_limits", "growth_ablation", "clamp_switch", "hybrid_same_customer", "block_total_grid", "call_cost_grid", "call_count_grid", "call_tokens_grid", "cost_curve", "feasible_grid"]


def test_registry():
    q, s = e.queries(), e.oracle_sql()
    assert set(s) <= set(q) and len(q) > 70
    if importlib.util.find_spec("semjoin.llm"):
        assert {n.split("_")[0] for n in q if n.startswith("op") and n[2].isdigit()} == {f"op{i}" for i in range(1, 11)} and "pipeline" in q


def test_engine_does_not_import_pipeline_operators():
    code = "import sys, semjoin.queries, semjoin.streaming, semjoin.sources; assert not any(m.startswith('semjoin.llm') for m in sys.modules)"
    assert subprocess.run([sys.executable, "-c", code], cwd=".").returncode == 0


def test_entry(spark):
    assert set(e.entry(spark).columns) == {"left_id", "right_id"}


@pytest.mark.parametrize("name", SMALL)
def test_against_sql(spark, name):
    c = duckdb.connect()
    for t in ("part", "orders", "documents", "labels", "embeddings", "benchmark", "supplier", "lineitem"):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = e.queries()[name](spark, SF)
    want = c.execute(e.oracle_sql()[name])
    names = [d[0] for d in want.description]
    assert sorted(names) == sorted(got.columns)
    norm = lambda rows: sorted([tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in rows], key=repr)
    assert norm(map(tuple, got.select(*names).collect())) == norm(want.fetchall())


def test_stream(spark, tmp_path):
    from semjoin.lm.models import TruthModel
    from semjoin.streaming import stream_semantic_join
    from tests.test_joins import LEFT, RIGHT, SAME, _truth
    from semjoin.sources import from_lists

    from_lists(spark, LEFT).repartition(3).write.parquet(str(tmp_path / "in"))
    arriving = spark.readStream.schema("row_id bigint, text string, key string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    query, carried = stream_semantic_join(arriving, from_lists(spark, RIGHT), SAME, TruthModel(SAME), str(tmp_path / "out"), str(tmp_path / "state"), 0.01)
    query.awaitTermination()
    assert len(carried.batches) == 3
    assert {(r["left_id"], r["right_id"]) for r in spark.read.parquet(str(tmp_path / "out")).collect()} == _truth(LEFT, RIGHT)


@pytest.mark.parametrize("name", ["block_total_grid", "call_cost_grid", "call_count_grid", "call_tokens_grid", "clamp_switch", "cost_curve", "cost_surface", "feasible_grid", "growth_ablation"])
def test_grids_come_from_a_table(spark, tmp_path, name):
    lines = spark.createDataFrame([(2.0, 1, 0.25), (2.0, 1, 0.25), (3.0, 2, 0.5)], "l_quantity double, l_linenumber int, l_discount double")
    lines.write.parquet(f"{tmp_path}/lineitem.parquet")
    got = e.queries()[name](spark, str(tmp_path))
    c = duckdb.connect()
    c.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    want = c.execute(e.oracle_sql()[name]).fetchall()
    assert len(want) == (4 if name == "cost_surface" else 2) and sorted(map(tuple, got.collect())) == sorted(want)
