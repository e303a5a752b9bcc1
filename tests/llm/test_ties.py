"""Repeated rows and ids, null ids and texts of several MB, for every operator."""

import hashlib
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from semjoin.llm import chat_format, embedding_dedup, exact_dedup, language, lm_scoring, ngram_join, packing, pii, sentencepiece_codec, substring_dedup

q = random.Random(5)
A = " ".join(f"w{q.randrange(60)}" for _ in range(90))
NEAR = A + " tail"
B = " ".join(f"v{q.randrange(900)}" for _ in range(80))
ROWS = [(5, A, "en"), (5, A, "en"), (5, A, "fr"), (3, NEAR, "en"), (7, B, "de"), (7, A, "de"), (None, A, "en"), (None, None, None), (9, "", "en"), (9, "", "en")]


@pytest.fixture(scope="module")
def rows(spark):
    return spark.createDataFrame(ROWS, "doc_id bigint, text string, lang string").repartition(3)


def test_exact_keeps_one_of_repeated_rows(spark, rows):
    named = [r for r in ROWS if r[0] is not None]
    df = spark.createDataFrame(named, rows.schema).repartition(3)
    got = [(x["doc_id"], x["keep_id"], x["group_size"], x["kept"]) for x in exact_dedup.group_equal(df).collect()]
    assert sorted(got) == sorted([(5, 5, 4, True), (5, 5, 4, False), (5, 5, 4, False), (3, 3, 1, True), (7, 7, 1, True), (7, 5, 4, False), (9, 9, 2, True), (9, 9, 2, False)])
    kept = sorted(tuple(x) for x in exact_dedup.deduplicate(df).collect())
    assert kept == sorted([(5, A, "en"), (3, NEAR, "en"), (7, B, "de"), (9, "", "en")])
    # A null id sorts first.
    assert sorted(((x["doc_id"], x["text"]) for x in exact_dedup.deduplicate(rows).collect()), key=str) == sorted([(None, A), (None, None), (3, NEAR), (7, B)], key=str)
    # One hash for all texts: they are compared themselves.
    same = lambda norm: (F.lit(1).cast("long"), F.lit(2).cast("long"))
    assert sorted(tuple(x) for x in exact_dedup.deduplicate(df, hash_of=same).collect()) == kept


def test_near_keeps_one_row(rows):
    got = [(x["doc_id"], x["n_shingles"], x["component_id"]) for x in ngram_join.cluster(rows).collect()]
    n = len({tuple(A.split()[i : i + 5]) for i in range(86)})
    # Of the two texts of 7 the first in order stands for both rows.
    assert sorted((x for x in got if x[0] is not None)) == sorted([(5, n, 3)] * 3 + [(3, n + 1, 3)] + [(7, 76, 7)] * 2 + [(9, 0, 9)] * 2)
    kept = sorted(x["doc_id"] for x in ngram_join.keep_one(rows.where("doc_id is not null")).collect())
    assert kept == [3, 7, 9]


def test_every_row_comes_back(rows):
    n = rows.count()
    assert pii.detect(rows).count() == pii.redact(rows).count() == n
    p = language.learn(rows)
    assert language.predict(rows, p).count() == n and language.accepted(rows, p).count() == 7
    assert language.accepted(rows, {}).count() == 7 and language.accepted(rows.limit(0), p).count() == 0
    assert sentencepiece_codec.encode(rows).count() == n
    assert lm_scoring.score(rows, F.lit(True)).count() == n
    pieces = packing.pack(rows).collect()
    assert len(pieces) == n and len({(x["sequence_id"], x["offset"]) for x in pieces}) == n
    cut = substring_dedup.remove_repeats(rows).collect()
    assert len(cut) == n and {x["n_removed"] for x in cut if x["doc_id"] == 5} == {90}


def test_repeated_vector_ids(spark):
    g = np.random.default_rng(2)
    a, b = g.standard_normal((2, 32))
    rows = [(1, a.tolist()), (1, b.tolist()), (2, (a + 0.01 * g.standard_normal(32)).tolist()), (4, a.tolist()), (3, b.tolist()), (None, b.tolist())]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").repartition(2)
    got = sorted(((x["vec_id"], x["n_links"], x["component_id"], x["kept"]) for x in embedding_dedup.link(df).collect()), key=str)
    assert got == sorted([(1, 2, 1, True), (1, 2, 1, True), (2, 2, 1, False), (4, 2, 1, False), (3, 2, 1, False), (None, 2, 1, False)], key=str)


def test_recall_at_the_threshold():
    """Pairs at a cosine of 0.95-0.96, where a miss is likeliest: the share that meets in a bucket is measured."""
    g = np.random.default_rng(1)
    a = embedding_dedup.unit_vectors(g.standard_normal((2000, 64)))
    r = g.standard_normal((2000, 64))
    r = embedding_dedup.unit_vectors(r - (r * a).sum(1, keepdims=True) * a)
    cos = g.uniform(0.95, 0.96, (2000, 1))
    b = cos * a + np.sqrt(1 - cos**2) * r
    met = (embedding_dedup.keys_of(a) == embedding_dedup.keys_of(embedding_dedup.unit_vectors(b))).any(1)
    assert met.mean() > 0.99


def test_texts_of_several_megabytes(spark):
    long = " ".join(f"x{q.randrange(5000)}" for _ in range(500_000))
    rows = spark.createDataFrame([(1, long), (2, long + " end"), (3, "short text of a few words only")], "doc_id bigint, text string")
    assert [x["component_id"] for x in ngram_join.cluster(rows).orderBy("doc_id").collect()] == [1, 1, 3]
    got = {x["doc_id"]: x for x in substring_dedup.remove_repeats(rows).collect()}
    assert [got[i]["n_removed"] for i in (1, 2, 3)] == [500_000, 500_000, 0] and got[2]["kept_sha256"] == hashlib.sha256(b"end").hexdigest()
    scored = {x["doc_id"]: x["n_tokens"] for x in lm_scoring.score(rows, F.lit(True)).collect()}
    assert scored == {1: 500_001, 2: 500_002, 3: 8}
    pieces = packing.pack(rows).groupBy("doc_id").agg(F.sum("length").alias("n"), F.max("doc_tokens").alias("m")).collect()
    assert all(x["n"] == x["m"] for x in pieces) and len(pieces) == 3
    assert exact_dedup.deduplicate(rows).count() == 3 and pii.detect(rows).count() == 3
    turns = spark.createDataFrame([(1, 0, "assistant", long)], "conv_id bigint, turn bigint, role string, text string")
    assert chat_format.read_back(chat_format.format_chats(turns)).first()["loss_chars"] == len(long)


def test_overlapping_control_strings(spark):
    marks = ["<|", "|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|>", "<", "|", ">", "[", "]", "\\", "s", "/", "\n"]
    rows = [(i, 0, "".join(q.choice(marks) for _ in range(q.randrange(5))), "".join(q.choice(marks) for _ in range(q.randrange(12)))) for i in range(3000)] + [(3000, 0, "<|>", "<|>")]
    f = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")
    made = {x["conv_id"]: x["formatted"] for x in chat_format.format_chats(f).collect()}
    assert {i: list(chat_format.parse(t)) for i, t in made.items()} == {i: [(role, text)] for i, _, role, text in rows}
    for t in made.values():
        assert t.startswith("<|") and t.endswith("</s>\n")
        assert [t[2:-5].count(m) for m in marks[:8]] == [0, 1, 0, 0, 0, 0, 0, 0]  # the closing of the header


def test_base_kinds_by_plain_expressions():
    """ip, card and phone against their definition on random texts, digest included."""
    import re

    def want(t):
        out = [("email", m.start(), m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
        out += [("ip", m.start(), m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))]
        digits = lambda s: re.sub("[^0-9]", "", s)
        out += [("card", m.start(), m.end()) for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t) if 16 <= len(digits(m[0])) <= 19 and pii.luhn(digits(m[0]))]
        return out + [("phone", m.start(), m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 8 <= len(digits(m[0])) <= 15]

    parts = ["1.2.3.4", "255.255.0.1.7", "4111 1111 1111 1111", "4111111111111111", "+1 (555) 010-99 88", "+", ".", "-", " ", "9", "300.1.1.1", "a@b.co", "@", "x.y@z", "12", "0"]
    texts = ["".join(q.choice(parts) for _ in range(q.randrange(1, 14))) for _ in range(20_000)]
    for t in texts:
        assert [s[:3] for s in pii.find(t) if s[0] in pii.BASE_KINDS] == want(t), t
    got = next(iter(pii._scan([pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array(texts)], ["doc_id", "text"])])))
    for i in (0, 17):
        base = want(texts[i])
        assert got.column(got.schema.get_field_index("base_sha256"))[i].as_py() == hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b in base).encode()).hexdigest()
        assert got.column(1)[i].as_py() == sum(k == "email" for k, _, _ in base)


def test_language_against_sums_of_single_trigrams(spark):
    """Predictions of a table by the definition, one trigram at a time."""
    texts = {"aa": ["abra cadabra", "arba abra"], "bb": ["xyzzy zyx", "yxz zzy"]}
    rows = [(i, t, lang) for i, (lang, t) in enumerate((x, t) for x, ts in texts.items() for t in ts)]
    probes = [(10, "abracad", None), (11, "zyxxy", None), (12, "", None), (13, "4711", None)]
    df = spark.createDataFrame(rows + probes, "doc_id bigint, text string, lang string")
    got = {x["doc_id"]: (x["lang_pred"], x["score"]) for x in language.predict(df, language.learn(df)).collect()}
    letters = language._letters()

    def vector(text):
        x = [0, *[int(language._symbols()[ord(c)]) for c in text], 0]
        return sum((letters[0][a] * letters[1][b] * letters[2][c] for a, b, c in zip(x, x[1:], x[2:])), np.zeros(language.DIMENSIONS))

    own = {k: sum(vector(f" {t} ".replace(" ", "\n")[1:-1]) for t in ts) for k, ts in texts.items()}
    for i, text in ((10, "abracad"), (11, "zyxxy")):
        v = vector(text)
        cos = {k: float(v @ u / np.linalg.norm(v) / np.linalg.norm(u)) for k, u in own.items()}
        assert got[i][0] == max(cos, key=cos.get) and got[i][1] == pytest.approx(max(cos.values()), rel=1e-5)
    assert got[12] == got[13] == ("und", 0.0)


def test_held_out_is_by_crc32(spark):
    got = spark.range(50).select("id", language.held_out(F.col("id")).alias("h"), lm_scoring.held_out(F.col("id")).alias("s")).collect()
    assert all((x["h"], x["s"]) == (zlib.crc32(str(x["id"]).encode()) % 4 == 2, zlib.crc32(str(x["id"]).encode()) % 10 == 0) for x in got)


def test_near_copies_do_not_cost_their_square(spark, monkeypatch):
    """Most copies are linked at once; what is left asks a few partners each, not all, and has the same components."""
    import random

    from semjoin.llm import ngram_join

    r = random.Random(1)
    base = [f"w{i}" for i in range(120)]
    texts = []
    for _ in range(400):
        t = list(base)
        for _ in range(int(r.random() * 5) + 1):
            t[r.randrange(len(t))] = f"x{r.randrange(10**6)}"
        texts.append(t)
    sets = [{tuple(t[i : i + 5]) for i in range(len(t) - 4)} for t in texts]
    root = list(range(len(sets)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            if 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    asked, plain = [], ngram_join._Join.measured
    monkeypatch.setattr(ngram_join._Join, "measured", lambda self, near: asked.append(near.count()) or plain(self, near))
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id bigint, text string")
    got = {x["doc_id"]: x["component_id"] for x in ngram_join.cluster(docs).collect()}
    assert got == {i: find(i) for i in range(len(sets))}
    assert sum(asked) < 2 * len(texts)


def test_few_links_are_contracted_in_few_steps(spark, monkeypatch):
    """Few links take two written tables, whatever their paths; more than a task holds take the distributed rounds, with the same result."""
    import random

    import numpy as np
    import pyarrow as pa

    from semjoin.llm import components as c
    from semjoin.llm.scratch import Scratch

    r = random.Random(2)
    pairs = [(i, i + 1) for i in range(300)] + [(r.randrange(1000, 1400), r.randrange(1000, 1400)) for _ in range(250)] + [(7, 7), (5000, 4000)]
    root = {x: x for p in pairs for x in p}
    for _ in root:
        for a, b in pairs:
            root[a] = root[b] = min(root[a], root[b])
    r.shuffle(pairs)
    links = spark.createDataFrame(pairs, "a bigint, b bigint").repartition(3)
    written, plain = [], Scratch.table
    monkeypatch.setattr(Scratch, "table", lambda self, df, name="t": written.append(name) or plain(self, df, name))
    own = lambda df: {x["node"]: x["component"] for x in df.collect()}
    joined = {n: m for n, m in root.items() if n != m or n in root.values()}
    got = own(c.components_of_few(links, Scratch(spark, "few")))
    assert written == ["forest"] and {n: got.get(n, n) for n in root} == joined
    monkeypatch.setattr(c, "HELD", 40)
    got = own(c.components_of_few(links, Scratch(spark, "few")))
    assert len(written) > 3 and {n: got.get(n, n) for n in root} == joined
    batches = [pa.RecordBatch.from_arrays([pa.array([p[0] for p in pairs[i : i + 25]]), pa.array([p[1] for p in pairs[i : i + 25]])], ["a", "b"]) for i in range(0, len(pairs), 25)]
    forest = list(c._forest(iter(batches)))  # a task that lets go of some
    node, least = c.roots(*(np.concatenate([np.asarray(x.column(k)) for x in forest]) for k in (0, 1)))
    assert len(forest) > 1 and {n: dict(zip(node.tolist(), least.tolist())).get(n, n) for n in root} == joined


def test_settling_takes_few_steps(spark, monkeypatch):
    """A group of near copies is joined in a bounded number of written tables, each of which costs a run of tasks."""
    import random

    from semjoin.llm.scratch import Scratch

    r = random.Random(3)
    base = [f"w{i}" for i in range(60)]
    texts = [list(base) for _ in range(300)]
    for t in texts:
        for _ in range(r.randrange(1, 4)):
            t[r.randrange(60)] = f"x{r.randrange(10**6)}"
    written, plain = [], Scratch.table
    monkeypatch.setattr(Scratch, "table", lambda self, df, name="t": written.append(name) or plain(self, df, name))
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id bigint, text string")
    assert ngram_join.cluster(docs).count() == 300
    assert written.count("said") <= 4 and "large" not in written
