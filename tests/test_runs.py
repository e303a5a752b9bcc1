"""Tasks that calls are dealt to, resumed runs, fee limits, rows as answers, packed batches, strict parsing."""

import pytest
from pyspark import TaskContext

from semjoin.functions import parse
from semjoin.lm.base import SameFeature, SemanticPredicate
from semjoin.lm.models import Answer, TruthModel
from semjoin.operators import embedding, joins
from semjoin.prompts import PromptStyle
from semjoin.sources import from_lists
from semjoin.types import FeeLimit, ModelProfile


def _first_word(text, key):
    return text.split()[0] if text.split() else None


SAME = SemanticPredicate("both start with the same word", SameFeature(_first_word, _first_word))
LEFT = [f"w{i % 5} left {i}" for i in range(40)]
RIGHT = [f"w{i % 7} right {i}" for i in range(21)]
TRUE = {(i, j) for i in range(40) for j in range(21) if i % 5 == j % 7}


class Where(TruthModel):
    """Says in the latency which task asked."""

    def complete(self, prompts):
        for a in super().complete(prompts):
            yield Answer(a.text, a.stopped, a.tokens_read, a.tokens_written, float(TaskContext.get().partitionId()))


class Counting(TruthModel):
    """Counts its calls in a file per call."""

    def complete(self, prompts):
        import os
        import uuid

        for a in super().complete(prompts):
            open(os.path.join(self.folder, uuid.uuid4().hex), "w").close()
            if self.fail_at and len(os.listdir(self.folder)) > self.fail_at:
                raise RuntimeError("lost")
            yield a


def _ids(run):
    return {tuple(r) for r in run.pairs.select("left_id", "right_id").collect()}


def _tasks(run):
    return run.ledger.select("latency_ms").distinct().count()


def test_calls_are_dealt_to_tasks(spark):
    m = Where(SAME, ModelProfile(8192))
    left, right = from_lists(spark, LEFT), from_lists(spark, RIGHT)
    for sizes, least in (((5, 7), 4), ((40, 3), 4), ((40, 21), 1), ((2, 21), 4)):
        run = joins.block_join(left, right, SAME, m, *sizes)
        assert _ids(run) == TRUE and _tasks(run) >= least
    run = joins.pairwise_join(left, right, SAME, m)
    assert _ids(run) == TRUE and _tasks(run) == 4
    run = joins.adaptive_join(left, right, SAME, Where(SAME, ModelProfile(200)), 0.01)
    assert _ids(run) == TRUE and _tasks(run) >= 4
    one = joins.block_join(left, right, SAME, Where(SAME, ModelProfile(8192, max_parallel=1)), 5, 7)
    assert _ids(one) == TRUE and _tasks(one) == 1
    keyed = [x.selectExpr("*", "row_id % 2 AS k") for x in (left, right)]
    hybrid = joins.hybrid_join(*keyed, "k", SAME, m, 2, 2)
    assert _ids(hybrid) == {(i, j) for i, j in TRUE if i % 2 == j % 2} and _tasks(hybrid) == 4


def test_a_hot_group_is_numbered_and_dealt_whole(spark):
    from pyspark.sql import functions as F

    from semjoin.operators import batching

    rows = spark.range(5000).select(F.col("id").alias("row_id"), F.lit("t").alias("text"), F.lit(None).cast("string").alias("key"), F.when(F.col("id") < 4000, 1).otherwise(F.col("id") % 7 + 2).alias("k"))
    b = batching.make_batches(rows, 10, by="k")
    sizes = b.groupBy("k").agg(F.sum(F.size("items")).alias("n"), F.count_if(F.size("items") < 10).alias("short")).collect()
    assert sum(x["n"] for x in sizes) == 5000 and all(x["short"] <= 1 for x in sizes)
    cells = batching.make_cells(b, b, on="k")
    got = cells.groupBy("k").agg(F.countDistinct("left_batch", "right_batch").alias("d"), F.count("*").alias("n")).collect()
    n = {x["k"]: x["n"] for x in b.groupBy("k").agg(F.count("*").alias("n")).collect()}
    assert all(x["d"] == x["n"] == n[x["k"]] ** 2 for x in got)


def test_rows_as_answers_in_every_join(spark):
    left, right = from_lists(spark, LEFT), from_lists(spark, RIGHT)
    style = PromptStyle(answer_form="rows")
    for restart in ("all", "failed"):
        assert _ids(joins.adaptive_join(left, right, SAME, TruthModel(SAME, ModelProfile(400)), 0.01, style=style, restart=restart)) == TRUE
    keyed = [x.selectExpr("*", "row_id % 2 AS k") for x in (left, right)]
    assert _ids(joins.hybrid_join(*keyed, "k", SAME, TruthModel(SAME), 5, 5, style)) == {(i, j) for i, j in TRUE if i % 2 == j % 2}


def test_rows_that_hold_the_mark_between_them(spark):
    left, right = from_lists(spark, ["w1 | x", "w1 x", "w2 | | y"]), from_lists(spark, ["w1 | z | z", "w2"])
    m = TruthModel(SAME, ModelProfile(8192))
    assert _ids(joins.block_join(left, right, SAME, m, 3, 2, PromptStyle(answer_form="rows"))) == {(0, 0), (1, 0), (2, 1)}


def test_every_operator_refuses_a_fee(spark):
    left, right = from_lists(spark, LEFT), from_lists(spark, RIGHT)
    m = TruthModel(SAME, ModelProfile(400))
    keyed = [x.selectExpr("*", "row_id % 2 AS k") for x in (left, right)]
    calls = [
        lambda fee: joins.pairwise_join(left, right, SAME, m, max_fee=fee),
        lambda fee: joins.pairwise_join(left, right, SAME, m, max_fee=fee, candidates=spark.createDataFrame([(0, 0), (1, 1)], "left_id bigint, right_id bigint")),
        lambda fee: joins.parallel_pairwise_engine(left, right, SAME, m, max_fee=fee),
        lambda fee: joins.block_join(left, right, SAME, m, 4, 4, max_fee=fee),
        lambda fee: joins.block_join_planned(left, right, SAME, m, max_fee=fee),
        lambda fee: joins.hybrid_join(*keyed, "k", SAME, m, 4, 4, max_fee=fee),
        lambda fee: joins.adaptive_join(left, right, SAME, m, 0.1, max_fee=fee),
        lambda fee: joins.adaptive_join(left, right, SAME, m, 0.9, direction="down", max_fee=fee),
    ]
    for call in calls:
        with pytest.raises(FeeLimit):
            call(1e-7)
        assert call(1e6).pairs.count() > 0
    with pytest.raises(ValueError):
        joins.adaptive_join(left, right, SAME, m, 0.9, direction="down", restart="failed")


def test_a_killed_run_is_resumed(spark, tmp_path):
    left, right = from_lists(spark, LEFT), from_lists(spark, RIGHT)
    folder, out = tmp_path / "calls", f"file://{tmp_path}/run"
    folder.mkdir()

    def run(fail_at=0, resume=out, **options):
        m = Counting(SAME, ModelProfile(200))
        m.folder, m.fail_at = str(folder), fail_at
        return joins.adaptive_join(left, right, SAME, m, 0.05, restart="failed", resume=resume, part_cells=10, **options)

    whole = run(resume=None)
    calls = whole.usage().first()["calls"]
    assert calls == len(list(folder.iterdir())) > 20
    for f in folder.iterdir():
        f.unlink()
    with pytest.raises(Exception):
        run(fail_at=calls // 2)
    before = len(list(folder.iterdir()))
    done = run()
    assert _ids(done) == _ids(whole) == TRUE and done.usage().first()["calls"] == calls
    assert len(list(folder.iterdir())) - before < 0.8 * calls  # finished parts are not asked again
    again = len(list(folder.iterdir()))
    assert _ids(run()) == TRUE and len(list(folder.iterdir())) == again
    with pytest.raises(ValueError):
        run(growth=2.0)


def test_packed_join(spark):
    left, right = from_lists(spark, LEFT), from_lists(spark, RIGHT)
    assert _ids(joins.packed_join(left, right, SAME, TruthModel(SAME), 40, 30)) == TRUE


def test_strict_parse(spark):
    make = lambda a: spark.createDataFrame([([10, 11], [20], a)], "left_ids array<bigint>, right_ids array<bigint>, answer string")
    assert [tuple(x) for x in parse.strict_parse(make("1,1; 2,1; DONE")).collect()] == [(10, 20), (11, 20)]
    for bad in ("1,1;3,1;", "0,1;", "Sure: 1,1;"):
        with pytest.raises(parse.BadPositions):
            parse.strict_parse(make(bad))


def test_the_nudge_is_a_switch(spark):
    on, off = PromptStyle(), PromptStyle(nudge=False)
    assert on.instruction_tokens("x") - off.instruction_tokens("x") == 4
    assert _ids(joins.block_join(from_lists(spark, LEFT), from_lists(spark, RIGHT), SAME, TruthModel(SAME, ModelProfile(8192)), 9, 9, off)) == TRUE


def test_texts_are_embedded_once(spark):
    seen = spark.sparkContext.accumulator(0)

    class Counted(embedding.HashingEmbedder):
        def vectors(self, texts):
            seen.add(len(texts))
            return super().vectors(texts)

    left, right = from_lists(spark, LEFT), from_lists(spark, RIGHT)
    run = embedding.embedding_join(left, right, Counted(64), direction="both")
    run.pairs.collect()
    run.pairs.collect()
    assert seen.value == len(LEFT) + len(RIGHT)
