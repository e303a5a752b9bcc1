"""Caches and replay, filters before the model, self and as-of joins, grids, sinks, windows of rows, streams with state."""

import pytest
from pyspark.sql import functions as F

from semjoin import sources
from semjoin.lm.cache import AnswerCache, RecordedOnly
from semjoin.lm.models import TruthModel
from semjoin.operators import joins, selection
from semjoin.sources import from_lists, grid
from semjoin.types import BudgetTooSmall, ModelProfile
from tests.test_runs import LEFT, RIGHT, SAME, TRUE, Counting, _ids


def test_answers_are_recorded_and_replayed(spark, tmp_path):
    left, right = from_lists(spark, LEFT), from_lists(spark, RIGHT)
    cache, folder = AnswerCache(f"file://{tmp_path}/answers"), tmp_path / "calls"
    folder.mkdir()
    m = Counting(SAME, ModelProfile(8192))
    m.folder, m.fail_at = str(folder), 0
    first = joins.block_join(left, right, SAME, m, 10, 7, cache=cache)
    assert _ids(first) == TRUE and len(list(folder.iterdir())) == 12 == first.usage().first()["calls"]
    paid = first.usage().first()["tokens_read"]
    again = joins.block_join(left, right, SAME, m, 10, 7, cache=cache)
    assert _ids(again) == TRUE and len(list(folder.iterdir())) == 12 and again.usage().first()["tokens_read"] == 0 < paid
    replayed = joins.block_join(left, right, SAME, RecordedOnly(ModelProfile(8192)), 10, 7, cache=cache)
    assert _ids(replayed) == TRUE
    with pytest.raises(Exception, match="not recorded"):
        joins.block_join(left, right, SAME, RecordedOnly(ModelProfile(8192)), 9, 7, cache=cache)
    # Equal prompts are asked once.
    twice = from_lists(spark, ["w1 a", "w1 a", "w2 b"])
    run = joins.pairwise_join(twice, from_lists(spark, ["w1 x"]), SAME, TruthModel(SAME), cache=AnswerCache(f"file://{tmp_path}/pairs"))
    assert _ids(run) == {(0, 0), (1, 0)} and run.ledger.where("tokens_read > 0").count() == 2
    assert _ids(joins.adaptive_join(left, right, SAME, m, 0.05, cache=cache)) == TRUE
    cache.forget(spark)
    assert cache.answers(spark).count() == 0


def test_filters_before_the_model(spark):
    left = spark.createDataFrame([(0, "w1 a", "k", 5), (1, None, "k", 5), (2, "", "k", 5), (3, "w1 " * 30, "k", 5), (4, "w1 b", "k", None), (5, "w1 c", "k", 9)], "row_id bigint, text string, key string, n int")
    right = from_lists(spark, ["w1 x"])
    run = selection.filtered_join(joins.pairwise_join, left, right, SAME, TruthModel(SAME), pre_filter_left="n < 7", max_tokens=10)
    assert _ids(run) == {(0, 0)} and run.usage().first()["calls"] == 1
    plan = selection.candidates_of(left, F.col("n") < 7, min_tokens=0)._jdf.queryExecution().optimizedPlan().toString()
    assert "Filter" in plan


def test_self_join_asks_each_pair_once(spark):
    rows = from_lists(spark, LEFT)
    run = selection.self_join(rows, SAME, TruthModel(SAME, ModelProfile(8192)), 8)
    assert _ids(run) == {(i, j) for i in range(40) for j in range(i + 1, 40) if i % 5 == j % 5}
    assert run.usage().first()["calls"] == 15


def test_as_of(spark):
    left = spark.createDataFrame([(1, "a", 5), (2, "a", 1), (3, "b", 9), (4, None, 9), (5, "a", 7)], "row_id int, who string, at int")
    right = spark.createDataFrame([(10, "a", 2), (11, "a", 5), (12, "a", 8), (13, "b", 10), (14, None, 1)], "row_id int, who string, at int")
    got = {x["row_id"]: x["right_id"] for x in selection.as_of(left, right, "who", "at", "at").collect()}
    assert got == {1: 11, 2: None, 3: None, 4: None, 5: 11}


def test_grouped_functions_in_sql(spark):
    selection.register_aggregates(spark)
    spark.createDataFrame([("a", 1000, 10), ("a", 500, 0), ("b", 0, 100)], "m string, r int, w int").createOrReplaceTempView("ledger_rows")
    assert {m: round(x, 9) for m, x in spark.sql("SELECT m, fee_sum(r, w, 3.0D, 6.0D) FROM ledger_rows GROUP BY m").collect()} == {"a": 4.56, "b": 0.6}
    assert spark.sql("SELECT f1_of(h, r, t) FROM VALUES (2, 4, 2) AS x(h, r, t)").first()[0] == pytest.approx(2 / 3)


def test_grids_and_sinks(spark):
    g = grid.grid(spark, 3, estimate=[0.1, 0.5], growth=[2, 4, 8])
    assert g.columns == ["estimate", "growth"] and {tuple(x) for x in g.collect()} == {(e, x) for e in (0.1, 0.5) for x in (2.0, 4.0, 8.0)}
    pairs = spark.createDataFrame([(1, 2)], "left_id bigint, right_id bigint")
    spark.sql("DROP TABLE IF EXISTS semjoin_test_pairs")
    for k in (0, 1):
        sources.write_table(pairs, "semjoin_test_pairs", "run", k)
    assert spark.table("semjoin_test_pairs").where("round = 1").count() == 1 and spark.table("semjoin_test_pairs").count() == 2
    spark.sql("DROP TABLE semjoin_test_pairs")
    from_lists(spark, ["x y"]).createOrReplaceTempView("semjoin_texts")
    assert sources.from_table(spark, "semjoin_texts", "row_id").first()["text"] == "x y"


def test_wide_rows(spark):
    m = TruthModel(SAME, ModelProfile(220))
    left, right = from_lists(spark, ["w1 " + "a " * 300, "w2 b"]), from_lists(spark, ["w1 c", "w2 d"])
    with pytest.raises(BudgetTooSmall):
        joins.fitting(left, right, SAME, m)
    cut = joins.fitting(left, right, SAME, m, "cut")
    assert _ids(joins.block_join(*cut, SAME, m, 1, 1)) == {(0, 0), (1, 1)}
    parts = joins.fitting(left, right, SAME, m, "chunk")
    run = joins.block_join(*parts, SAME, m, 1, 1)
    assert {tuple(x) for x in joins.whole_rows(run.pairs, *parts).collect()} == {(0, 0), (1, 1)}


def test_a_restarted_stream_goes_on_with_its_estimate(spark, tmp_path):
    from semjoin.streaming import stream_semantic_join

    def start():
        arriving = spark.readStream.schema("row_id bigint, text string, key string").parquet(str(tmp_path / "in"))
        m = TruthModel(SAME, ModelProfile(300))
        query, carried = stream_semantic_join(arriving, from_lists(spark, ["w y"] * 11), SAME, m, str(tmp_path / "out"), str(tmp_path / "state"), 0.001)
        before = carried.estimate
        query.awaitTermination()
        return before, carried.estimate

    from_lists(spark, ["w x"] * 12).write.parquet(str(tmp_path / "in"))
    before, reached = start()
    assert before == 0.001 < reached
    spark.createDataFrame([(100 + i, "w z", None) for i in range(5)], "row_id bigint, text string, key string").write.mode("append").parquet(str(tmp_path / "in"))
    assert start()[0] == reached
    assert spark.read.parquet(str(tmp_path / "out")).select("left_id", "right_id").distinct().count() == 17 * 11


def test_two_streams_and_late_rows(spark, tmp_path):
    from semjoin.streaming import stream_stream_semantic_join, windowed_counts

    schema = "row_id bigint, text string, key string, at timestamp"

    def write(side, rows):
        spark.sql("SELECT 1")
        spark.createDataFrame([(i, t, None, at) for i, t, at in rows], "row_id bigint, text string, key string, at string").withColumn("at", F.col("at").cast("timestamp")).coalesce(1).write.mode("append").parquet(str(tmp_path / side))

    def run():
        l, r = (spark.readStream.schema(schema).parquet(str(tmp_path / s)) for s in ("l", "r"))  # noqa: E741
        stream_stream_semantic_join(l, r, "at", "10 minutes", "30 minutes", SAME, TruthModel(SAME, ModelProfile(8192)), str(tmp_path / "out"), str(tmp_path / "state")).awaitTermination()

    write("l", [(1, "a x", "2024-01-01 10:01:00"), (2, "b x", "2024-01-01 10:02:00"), (3, "a y", "2024-01-01 10:31:00")])
    write("r", [(1, "a r", "2024-01-01 10:09:00"), (2, "b r", "2024-01-01 10:12:00")])
    run()
    write("r", [(3, "b late", "2024-01-01 10:08:00"), (4, "a s", "2024-01-01 10:39:00")])  # late, within the delay
    run()
    assert {(x["left_id"], x["right_id"]) for x in spark.read.parquet(str(tmp_path / "out")).collect()} == {(1, 1), (2, 3), (3, 4)}
    counts = windowed_counts(spark.read.schema(schema).parquet(str(tmp_path / "r")), "at", "10 minutes", "0 minutes").collect()
    assert sorted(x["n_rows"] for x in counts) == [1, 1, 2]


def test_batches_fill_across_micro_batches(spark, tmp_path):
    from semjoin.streaming import stateful_batches

    for k in range(3):
        spark.createDataFrame([(10 * k + i, f"t{i}", "ab"[i % 2]) for i in range(5)], "row_id bigint, text string, who string").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("row_id bigint, text string, who string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = stateful_batches(stream, "who", 4).writeStream.format("parquet").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start(str(tmp_path / "out"))
    q.awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out")).collect()
    # Nine rows of a and six of b: two full batches and one.
    assert sorted((x["who"], x["batch_id"], len(x["row_ids"])) for x in got) == [("a", 0, 4), ("a", 1, 4), ("b", 0, 4)]


def test_figures_run_anew_and_only_what_is_asked(spark, monkeypatch):
    """A second query of a session reads its tables itself."""
    from semjoin import figures

    class Run:
        seconds = 1.0

        def usage(self):
            return spark.createDataFrame([(1, 2, 3, 4.0)], "calls bigint, tokens_read bigint, tokens_written bigint, latency_ms double")

    asked = []
    monkeypatch.setattr(figures, "_run", lambda x, m: asked.append((x.name, m)) or Run())
    for _ in range(2):
        assert figures.operators_latency(spark, "/root/testdata/sf0.001").count() == 15
    assert len(asked) == 30 and "informed" not in {m for _, m in asked}
