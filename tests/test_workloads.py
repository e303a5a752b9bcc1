"""Workloads keep all true pairs, whatever the tables' sizes."""

import duckdb
import pytest
from pyspark.sql import functions as F

from semjoin import queries, workloads


def _quoted(spark, path, docs, marks):
    spark.createDataFrame(docs, "doc_id bigint, text string").write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(marks, "item_id bigint, text string").write.parquet(f"{path}/benchmark.parquet")
    w = workloads.quotes(spark, str(path))
    pairs = w.left.alias("l").join(w.right.alias("r"), F.contains("l.text", "r.text")).select(F.col("l.row_id").alias("left_id"), F.col("r.row_id").alias("right_id"))
    return w, pairs


def test_wide_passages_lie_in_a_chunk(spark, tmp_path):
    words = [f"w{i}" for i in range(3000)]
    docs = [(1, " ".join(words)), (2, "short")]
    marks = [(k, " ".join(words[a : a + n])) for k, (a, n) in enumerate([(200, 150), (350, 119), (500, 700), (2300, 700), (270, 20)])] + [(9, " " + " ".join(words[279:978]))]
    w, pairs = _quoted(spark, tmp_path, docs, marks)
    want = {tuple(x) for x in w.truth.collect()}
    assert len(want) == 6 and {(x["doc_id"], x["item_id"]) for x in workloads.documents_of(pairs).collect()} == want


def test_many_chunks_keep_their_document(spark, tmp_path):
    docs = [(1, " ".join(f"w{i}" for i in range(285_000))), (2, "other words")]
    w, pairs = _quoted(spark, tmp_path, docs, [(7, "w284800 w284801"), (8, "other")])
    assert {tuple(x) for x in workloads.documents_of(pairs, w.stride).collect()} == {(1, 7), (2, 8)}


def test_long_conversations_have_ids_of_their_own(spark, tmp_path):
    rows = [(conv, turn, "assistant" if turn % 2 else "user", f"{conv} {turn}") for conv, n in ((1, 2400), (2, 600), (3, 4)) for turn in range(n)]
    spark.createDataFrame(rows, "conv_id bigint, turn int, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    w = workloads.replies(spark, str(tmp_path))
    ids = [x[0] for x in w.left.select("row_id").union(w.right.select("row_id")).collect()]
    assert len(set(ids)) == len(ids) == len(rows) and w.truth.distinct().count() == len(rows) // 2


@pytest.mark.parametrize("name", ["semantic_filter_quality", "toxic_whole"])
def test_all_labelled_documents_are_asked_about(spark, tmp_path, name):
    """More than 100 labels, and texts of several chunks."""
    docs = [(i, " ".join(["word"] * (5 if i % 7 else 1300))) for i in range(260)]
    spark.createDataFrame(docs, "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, i % 3 % 2, int(i % 5 == 0)) for i in range(0, 260, 1) if i % 11], "doc_id bigint, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    con = duckdb.connect()
    for t in ("documents", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
    want = sorted(con.execute(queries.SQL[name]).fetchall())
    assert len(want) > 60 and sorted(map(tuple, queries.QUERIES[name](spark, str(tmp_path)).collect())) == want


def _folders(spark, path, tables):
    """Tables as Spark writes them: folders of files that are all named part-*."""
    for t in tables:
        spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet").repartition(2).write.parquet(f"{path}/{t}.parquet")


def _by_sql(path, name):
    con = duckdb.connect()
    for t in sorted(path.glob("*.parquet")):
        con.execute(f"CREATE VIEW {t.stem} AS SELECT * FROM '{t}/*.parquet'")
    return con.execute(queries.SQL[name]).fetchall()


def test_stream_reads_parts_only(spark, tmp_path):
    _folders(spark, tmp_path, ("part", "supplier", "orders"))
    got = queries.QUERIES["stream_replay_equals_batch"](spark, str(tmp_path)).select("left_id", "right_id").collect()
    assert len(got) == 200 and sorted(map(tuple, got)) == sorted(_by_sql(tmp_path, "stream_replay_equals_batch"))


@pytest.mark.parametrize("method", ["block", "adaptive"])
def test_calls_grow_with_the_turns_not_their_square(spark, tmp_path, method):
    rows = [(conv, turn, "assistant" if turn % 2 else "user", " ".join(f"w{k}" for k in range(100))) for conv in range(400) for turn in range(4 if conv else 200)]
    spark.createDataFrame(rows, "conv_id bigint, turn int, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    w, run = queries._replies(spark, str(tmp_path), method)
    assert run.rounds[0].calls < 400  # all batches of both sides would meet in 1,000 and more
    assert sorted(map(tuple, run.pairs.collect())) == sorted(map(tuple, w.truth.collect())) == sorted(_by_sql(tmp_path, f"replies_{method}"))


def test_classes_are_asked_about_with_one_row_each(spark, tmp_path, monkeypatch):
    """A language that the first pages don't have, documents without one, and far fewer calls than all pairs need."""
    from semjoin.operators import joins

    langs = ["en"] * 80 + ["fr"] * 15 + ["de"] * 5
    spark.createDataFrame([(i, f"http://host/{x}/{i}", "") for i, x in enumerate(langs)], "page_id bigint, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    docs = [(i, " ".join(f"w{k}" for k in range(900 if i % 9 == 0 else 150)), ("en", "de", "es", None, "fr")[i % 5]) for i in range(150)]
    spark.createDataFrame(docs, "doc_id bigint, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    calls, plain = [], joins.adaptive_join

    def counted(*args, **options):
        run = plain(*args, **options)
        calls.append((args[0].count(), args[1].count()))
        return run

    monkeypatch.setattr(joins, "adaptive_join", counted)
    got = sorted(map(tuple, queries.QUERIES["language_adaptive"](spark, str(tmp_path)).collect()))
    assert got == sorted(_by_sql(tmp_path, "language_adaptive")) and len(got) == 30 * 100
    assert sum(n * m for n, m in calls) < 100 * 150 // 2


def test_pairs_of_a_class_are_dealt_to_several_tasks(spark):
    from semjoin.operators import variants

    left = spark.range(60).selectExpr("id as left_id", "id % 10 = 0 as toxic")
    right = spark.range(50).selectExpr("id as right_id", "id % 5 = 0 as toxic")
    plan = variants.within_classes(left, right, "toxic")
    want = left.join(right, "toxic").select("left_id", "right_id")
    assert plan.exceptAll(want).isEmpty() and want.exceptAll(plan).isEmpty()
    assert "way" in plan._jdf.queryExecution().optimizedPlan().toString()


def test_chunks_carry_their_language_and_are_moved_once(spark, tmp_path):
    """Texts were joined with their own documents for the language, and batches of many texts moved twice."""
    from semjoin.operators import batching, joins
    from semjoin.plans.profile import profile_tables

    spark.createDataFrame([(1, "http://host/en/1", "")], "page_id bigint, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    docs = [(i, " ".join(f"w{k}" for k in range(900 if i % 9 == 0 else 50)), ("en", None)[i % 2]) for i in range(300)]
    spark.createDataFrame(docs, "doc_id bigint, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    w = workloads.language(spark, str(tmp_path))
    assert "Join" not in w.right._jdf.queryExecution().optimizedPlan().toString()
    assert [x["n"] for x in w.right.groupBy("key").count().withColumnRenamed("count", "n").orderBy("key").collect()] == [150 + 2 * 17, 150 + 2 * 17]
    written = []

    def keep(x):
        written.append(x)
        x.write.parquet(f"{tmp_path}/kept{len(written)}")
        return spark.read.parquet(f"{tmp_path}/kept{len(written)}")

    sides = tuple(batching.indexed(x, keep=keep) for x in (w.right, w.left))
    cells = joins._cells(sides, (2, 1), profile_tables(w.right, w.left), 4)
    assert len(written) == 2 and "RepartitionByExpression" not in cells._jdf.queryExecution().optimizedPlan().toString().split("Aggregate")[0]
    ids = [x["row_id"] for c in cells.collect() for x in c["left_items"]]
    assert sorted(ids) == sorted(x["row_id"] for x in w.right.collect())


def test_pairs_of_a_class_take_little_room(spark, tmp_path):
    """Pairs came in any order, in 4 bytes and more each."""
    from semjoin.operators import variants

    side = lambda name, n: spark.range(n).selectExpr(f"id * 7919 % 1000003 as {name}", "id % 4 = 0 as toxic")
    pairs = variants.within_classes(side("left_id", 2000), side("right_id", 3000), "toxic")
    pairs.write.parquet(f"{tmp_path}/pairs")
    n = 500 * 750 + 1500 * 2250
    assert spark.read.parquet(f"{tmp_path}/pairs").distinct().count() == pairs.count() == n
    assert sum(f.stat().st_size for f in (tmp_path / "pairs").glob("*.parquet")) < n


def test_labelled_texts_are_fetched_once(spark, tmp_path, monkeypatch):
    """Every pass over the chunks joined all documents with their labels anew, and twice."""
    from semjoin.operators import joins

    spark.createDataFrame([(i, " ".join(["word"] * (900 if i % 7 == 0 else 5))) for i in range(40)], "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 0, int(i % 5 == 0)) for i in range(0, 40, 2)], "doc_id bigint, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    asked, plain = [], joins.semantic_filter
    monkeypatch.setattr(joins, "semantic_filter", lambda rows, *args, **options: asked.append(rows) or plain(rows, *args, **options))
    got = sorted(map(tuple, queries.QUERIES["toxic_whole"](spark, str(tmp_path)).collect()))
    assert got == sorted(_by_sql(tmp_path, "toxic_whole")) == []  # no odd document has a label
    assert asked[0].count() == 20 + 2 * 3 and "Join" not in asked[0]._jdf.queryExecution().optimizedPlan().toString()
