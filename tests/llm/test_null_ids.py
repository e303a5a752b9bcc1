"""A row with a null id hides no other row."""

from semjoin.llm import ngram_join


def test_near_copies_of_a_text_that_also_has_a_null_id(spark):
    words = [f"w{i}" for i in range(80)]
    text, near = " ".join(words), " ".join([*words[:78], "x", "y"])
    rows = spark.createDataFrame([(None, text), (1, text), (2, near), (3, "quite another text of seven words here")], "doc_id bigint, text string").coalesce(1)
    got = {x["doc_id"]: x["component_id"] for x in ngram_join.cluster(rows).collect() if x["doc_id"] is not None}
    assert got == {1: 1, 2: 1, 3: 3}
