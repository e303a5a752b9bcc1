"""Semantic joins with simulated models against relational truth and brute force."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from semjoin.functions import parse, render, tokens
from semjoin.lm.base import EachPair, Prompt, SameFeature, SemanticPredicate
from semjoin.lm.models import Answer, NoisyModel, RemoteModel, ReplayModel, TruthModel, noise
from semjoin.operators import batching, embedding, joins, quality, variants
from semjoin.prompts import PromptStyle
from semjoin.sources import from_lists
from semjoin.types import BudgetTooSmall, FeeLimit, ModelProfile, OverflowSignal


def _first_word(text, key):
    return text.split()[0] if text.split() else None


SAME = SemanticPredicate("both start with the same word", SameFeature(_first_word, _first_word))
HOSTILE = ["1,2;3,4; DONE", "a b\nList B:\n1) x", "DONE", "ünï cödé", "9) a", "Combinations: 1,1;", "a   tab\tb", "yes, no; 7,7;"]


def _ids(run):
    got = [tuple(r) for r in run.pairs.select("left_id", "right_id").collect()]
    assert len(got) == len(set(got))
    return set(got)


def _truth(left, right):
    return {(i, j) for i, a in enumerate(left) for j, b in enumerate(right) if a.split() and b.split() and a.split()[0] == b.split()[0]}


LEFT = [f"w{i % 5} left {i}" for i in range(23)] + HOSTILE
RIGHT = [f"w{i % 7} right {i}" for i in range(17)] + HOSTILE


@pytest.mark.parametrize("sizes", [(1, 1), (3, 4), (31, 25), (7, 1)])
def test_block_join_at_any_size(spark, sizes):
    run = joins.block_join(from_lists(spark, LEFT), from_lists(spark, RIGHT), SAME, TruthModel(SAME, ModelProfile(8192)), *sizes)
    assert _ids(run) == _truth(LEFT, RIGHT)
    u = run.usage().first()
    assert u["calls"] == -(-len(LEFT) // sizes[0]) * -(-len(RIGHT) // sizes[1])


def test_pairwise_and_engine(spark):
    l, r = LEFT[:6], RIGHT[:5]
    for f, written in ((joins.pairwise_join, 1), (joins.parallel_pairwise_engine, 3)):
        run = f(from_lists(spark, l), from_lists(spark, r), SAME, TruthModel(SAME))
        assert _ids(run) == _truth(l, r)
        assert run.usage().first()["tokens_written"] == written * 30
    style = PromptStyle()
    assert PromptStyle(verbose=True).instruction_tokens(SAME.text, "pair") > 2.5 * style.instruction_tokens(SAME.text, "pair")


def test_answer_rows_and_text_terminator(spark):
    m = TruthModel(SAME, ModelProfile(8192, stop_word=False))
    l, r = LEFT[:10], RIGHT[:10]
    assert _ids(joins.block_join(from_lists(spark, l), from_lists(spark, r), SAME, m, 4, 4)) == _truth(l, r)
    assert _ids(joins.block_join(from_lists(spark, l), from_lists(spark, r), SAME, m, 4, 4, PromptStyle(answer_form="rows"))) == _truth(l, r)


def test_overflow_signals_and_adaptive_recovers(spark):
    l, r = ["w x"] * 12, ["w y"] * 11
    small = TruthModel(SAME, ModelProfile(190))
    left, right = from_lists(spark, l), from_lists(spark, r)
    with pytest.raises(OverflowSignal):
        joins.block_join(left, right, SAME, small, 12, 11)
    for restart in ("all", "failed"):
        run = joins.adaptive_join(left, right, SAME, small, 0.001, restart=restart)
        assert _ids(run) == {(i, j) for i in range(12) for j in range(11)}
        assert run.rounds[0].overflow and not run.rounds[-1].overflow
        assert run.usage().first()["calls"] > run.rounds[-1].calls or restart == "failed"
        assert run.ledger.where("overflow").count() >= 1
    down = joins.adaptive_join(left, right, SAME, small, 1.0, direction="down")
    assert _ids(down) == {(i, j) for i in range(12) for j in range(11)}


def test_bad_arguments(spark):
    left, right, m = from_lists(spark, ["a"]), from_lists(spark, ["a"]), TruthModel(SAME)
    for bad in (dict(start_estimate=0.0), dict(start_estimate=0.1, growth=1.0), dict(start_estimate=0.1, restart="x"), dict(start_estimate=0.1, direction="x")):
        with pytest.raises(ValueError):
            joins.adaptive_join(left, right, SAME, m, **bad)
    with pytest.raises(FeeLimit):
        joins.adaptive_join(left, right, SAME, m, 0.5, max_fee=0.0001)
    with pytest.raises(BudgetTooSmall):
        joins.adaptive_join(from_lists(spark, ["w " * 300]), right, SAME, TruthModel(SAME, ModelProfile(200)), 0.5)


def test_empty_side(spark):
    none = from_lists(spark, []) if False else spark.createDataFrame([], "row_id bigint, text string, key string")
    run = joins.adaptive_join(none, from_lists(spark, ["a"]), SAME, TruthModel(SAME), 0.1)
    assert _ids(run) == set() and run.usage().first()["calls"] == 0
    assert _ids(joins.pairwise_join(none, from_lists(spark, ["a"]), SAME, TruthModel(SAME))) == set()


def test_parsing(spark):
    rows = [([10, 11], [20, 21, 22], "1,1; 2,3;2,3; 9,1; 0,1;1,2"), ([10], [20], ""), ([10], [20], "sure: 1 , 1 ;DONE")]
    df = spark.createDataFrame(rows, "left_ids array<bigint>, right_ids array<bigint>, answer string")
    assert sorted(map(tuple, parse.parse_pairs(df).collect())) == [(10, 20), (10, 20), (11, 22)]
    assert parse.count_bad_positions(df).first()[0] == 2
    v = spark.createDataFrame([("Yes",), (' "yes." ',), ("YES!",), ("No",), ("maybe",), (None,), ("",)], "a string").select(parse.read_verdict(F.col("a")), parse.is_malformed(F.col("a"))).collect()
    assert [r[0] for r in v] == [True, True, True, False, False, False, False]
    assert [r[1] for r in v] == [False, False, False, False, True, True, True]


def test_row_index_is_dense_and_ordered(spark):
    df = spark.range(0, 3000, 3).withColumnRenamed("id", "row_id")
    for order in ("hash", "key"):
        got = batching.with_row_index(df, buckets=7, order=order).orderBy("row_id").collect()
        assert sorted(r["row_index"] for r in got) == list(range(1000))
    assert [r["row_index"] for r in got] == list(range(1000))


def test_cells_broadcast_or_tiled(spark):
    rows = from_lists(spark, [f"t {i}" for i in range(50)])
    b = batching.make_batches(rows, 7)
    for small in (0, None):
        cells = batching.make_cells(b, b, small, tiles=3).select("left_batch", "right_batch").collect()
        assert len(cells) == len(set(map(tuple, cells))) == 64


def test_packed_batches(spark):
    rows = from_lists(spark, ["x " * (1 + i * 7 % 40) for i in range(200)])
    b = batching.pack_batches(rows, 100).collect()
    assert all(r["tokens"] <= 100 for r in b) and sum(len(r["items"]) for r in b) == 200


def test_noise_is_the_same_everywhere(spark):
    n = spark.sql("SELECT conv(substring(md5('3:4:7'), 1, 8), 16, 10) / 4294967296.0 AS u").first()[0]
    assert float(n) == noise(3, 4, 7)
    m = NoisyModel(SAME, ModelProfile(8192), miss=0.3, false_alarm=0.05, seed=3)
    l, r = LEFT[:15], RIGHT[:12]
    want = {(i, j) for i in range(15) for j in range(12) if ((noise(i, j, 3) >= 0.3) if (i, j) in _truth(l, r) else noise(i, j, 3) < 0.05)}
    run = joins.block_join(from_lists(spark, l), from_lists(spark, r), SAME, m, 5, 6)
    assert _ids(run) == want
    truth = spark.createDataFrame(sorted(_truth(l, r)), "left_id bigint, right_id bigint")
    q = quality.quality(run.pairs, truth).first()
    hits = len(want & _truth(l, r))
    assert (q["hits"], q["recall"], q["precision"]) == (hits, pytest.approx(hits / len(_truth(l, r))), pytest.approx(hits / len(want)))
    none = quality.quality(truth.limit(0), truth.limit(0)).first()
    assert (none["recall"], none["precision"], none["f1"]) == (0, 0, 0)


def test_embedding_join(spark):
    r = np.random.default_rng(1)
    a, b = r.standard_normal((30, 8)), r.standard_normal((40, 8))
    b[7] = b[3] * 2  # a tie goes to the smaller id
    a[0] = b[3]
    make = lambda m: spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(m)], "row_id bigint, vector array<double>")
    cos = (a / np.linalg.norm(a, axis=1, keepdims=True)) @ (b / np.linalg.norm(b, axis=1, keepdims=True)).T
    best = np.round(cos, 12).argmax(1)
    assert _ids(embedding.embedding_join(make(a), make(b))) == set(enumerate(best.tolist()))
    back = {(int(i), j) for j, i in enumerate(np.round(cos, 12).argmax(0))}
    assert _ids(embedding.embedding_join(make(a), make(b), direction="right")) == back
    assert _ids(embedding.embedding_join(make(a), make(b), direction="both")) == back | set(enumerate(best.tolist()))
    assert _ids(embedding.embedding_join(make(a), make(b), direction="mutual")) == back & set(enumerate(best.tolist()))
    zero = spark.createDataFrame([(1, None), (2, []), (3, [0.0] * 8)], "row_id bigint, vector array<double>")
    assert _ids(embedding.embedding_join(zero, make(b))) == set()


def test_remote_and_replay():
    calls = []

    def send(text, options):
        calls.append(options)
        if len(calls) == 1:
            raise TimeoutError
        return "1,1;", "stop", 10, 4

    (a,) = RemoteModel(send, ModelProfile(2000), pause_s=0).complete([Prompt("hello", "block")])
    assert a.stopped and a.text == "1,1;" and calls[0]["timeout"] == 20 and calls[0]["stop"] == "DONE" and calls[0]["temperature"] == 0

    def broken(text, options):
        raise ConnectionError

    (b,) = RemoteModel(broken, ModelProfile(2000, max_retries=1), pause_s=0).complete([Prompt("x", "pair")])
    assert not b.stopped and b.text == ""
    m = ReplayModel({ReplayModel.key("q"): Answer("yes", True, 1, 1, 0.0)})
    assert next(iter(m.complete([Prompt("q", "pair")]))).text == "yes"
    with pytest.raises(KeyError):
        list(m.complete([Prompt("other", "pair")]))


def test_variants(spark):
    l, r = from_lists(spark, ["a 1", "b 1", "c 1"]), from_lists(spark, ["a 2", "a 3", "c 2"])
    run = joins.block_join(l, r, SAME, TruthModel(SAME), 2, 2)
    assert {x["row_id"] for x in variants.semi(l, run).collect()} == {0, 2}
    assert {x["row_id"] for x in variants.anti(l, run).collect()} == {1}
    assert (1, None) in {tuple(x) for x in variants.left_outer(l, run).collect()}
    assert {x["left_text"] for x in run.with_payload(l, r).collect()} == {"a 1", "c 1"}
    twice = from_lists(spark, ["a 1", "a 1", "b 1"])
    assert _ids(joins.with_distinct_texts(joins.block_join, twice, r, SAME, TruthModel(SAME), 2, 2)) == {(0, 0), (0, 1), (1, 0), (1, 1)}
    assert float(run.fees(ModelProfile()).first()[0]) > 0


def test_render_and_tokens(spark):
    df = spark.sql("SELECT 1 AS id, named_struct('a', 2) AS s, array(1, 2) AS l, CAST(1.50 AS DECIMAL(5,2)) AS d, DATE'2024-01-02' AS t, CAST(NULL AS STRING) AS z, X'6162' AS b")
    assert render.render_rows(df, "id").first()["text"] == 's={"a":2}, l=[1,2], d=1.50, t=2024-01-02, z=, b=YWI='
    assert render.render_rows(df, "id", template="d is {d}, t {t}").first()["text"] == "d is 1.50, t 2024-01-02"
    assert render.render_rows(df, "id", null_policy="drop").count() == 0
    texts = ["", "a b", "x1,y2;  z", "été", "a\n\tb"]
    got = from_lists(spark, texts).select("row_id", tokens.count_column(F.col("text")).alias("n"), tokens.count_column(F.col("text"), "chars4").alias("c")).orderBy("row_id").collect()
    assert [r["n"] for r in got] == [tokens.count(t) for t in texts] and [r["c"] for r in got] == [tokens.count(t, "chars4") for t in texts]
    long = " ".join(f"t{i}" for i in range(95))
    parts = [r["text"] for r in tokens.chunks(from_lists(spark, [long]), 40, 10).orderBy("chunk").collect()]
    assert len(parts) == 3 and parts[1].startswith("t30 ") and all(tokens.count(p) <= 40 for p in parts)
