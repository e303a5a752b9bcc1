"""The pipeline operators against brute force on small tables with nulls, ties, repeats and odd texts."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from semjoin.llm import chat_format, embedding_dedup, exact_dedup, language, lm_scoring, ngram_join, packing, pii, sentencepiece_codec, substring_dedup
from semjoin.llm.components import components
from semjoin.llm.scratch import Scratch

WORD = re.compile("[^\x20\x09-\x0d]+")
LOWER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
r = random.Random(11)
VOCAB = [f"Word{i}" for i in range(40)] + ["été", "x,", " ", "中文"]


def _text(n):
    return " ".join(r.choice(VOCAB) for _ in range(n))


BASE = [_text(n) for n in (60, 80, 200, 7, 5, 4, 1, 90)]
PASSAGE = _text(50)
TEXTS = [
    *BASE, BASE[0], BASE[0].replace(" ", "\n\t", 3), None, "", " \n ", BASE[1].upper(), " ".join(BASE[2].split()[:190] + ["new"] * 6), f"{_text(20)} {PASSAGE} {_text(10)}",
    f"{_text(3)} {PASSAGE}", PASSAGE + " " + PASSAGE, "a" * 5000, _text(3000), "+", "no words here?", BASE[3], BASE[5].lower(),
]
ROWS = [(i, t, ["en", "fr", None][i % 3], i * 2, 7) for i, t in enumerate(TEXTS)]


@pytest.fixture(scope="module")
def docs(spark):
    """Columns beside id and text have names that operators use themselves."""
    return spark.createDataFrame(ROWS, "doc_id bigint, text string, lang string, n bigint, part int").repartition(3)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.limit(0)


def _by_id(df, *cols, key="doc_id"):
    rows = df.collect()
    assert len({x[key] for x in rows}) == len(rows)
    return {x[key]: tuple(x[c] for c in cols) for x in rows}


def test_exact(spark, docs, empty):
    def want():
        norm = {i: re.sub("[\x20\x09-\x0d]+", " ", t or "") for i, t in enumerate(TEXTS)}
        out = {}
        for i, t in norm.items():
            same = [j for j, u in norm.items() if u == t]
            out[i] = (min(same), len(same), i == min(same), hashlib.sha256(t.encode()).hexdigest())
        return out

    cols = ("keep_id", "group_size", "kept", "text_sha256")
    assert _by_id(exact_dedup.group_equal(docs), *cols) == want()
    weak = lambda norm: (F.length(norm).cast("long"), F.lit(0).cast("long"))  # noqa: E731  texts of one length collide
    assert _by_id(exact_dedup.group_equal(docs, hash_of=weak), *cols) == want()
    assert exact_dedup.group_equal(empty).count() == 0
    kept = exact_dedup.deduplicate(docs)
    assert kept.columns == docs.columns and {x["doc_id"] for x in kept.collect()} == {i for i, v in want().items() if v[2]}


def _sets():
    out = {}
    for i, t in enumerate(TEXTS):
        w = WORD.findall((t or "").translate(LOWER))
        out[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    return out


def _components(nodes, links):
    p = {x: x for x in nodes}

    def find(x):
        while p[x] != x:
            x = p[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        p[max(a, b)] = min(a, b)
    return {x: find(x) for x in nodes}


def test_ngram_join(spark, docs, empty):
    sets = _sets()
    links = [(a, b) for a in sets for b in sets if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    comp = _components(sets, links)
    assert _by_id(ngram_join.cluster(docs), "n_shingles", "component_id") == {i: (len(sets[i]), comp[i]) for i in sets}
    assert ngram_join.cluster(empty).count() == 0
    assert {x["doc_id"] for x in ngram_join.keep_one(docs).collect()} == {i for i in sets if comp[i] == i}


def test_ngram_join_chains(spark):
    """Near copies that link only through others, and pairs at the threshold."""
    q = random.Random(2)
    base = [f"t{i}" for i in range(300)]
    texts = []
    for c in range(6):
        cur = [f"{x}c{c}" for x in base[: q.randint(40, 250)]]
        for k in range(12):
            cur = list(cur)
            for _ in range(q.randint(0, 4)):
                cur[q.randrange(len(cur))] = f"e{c}{k}{q.random()}"
            texts.append(" ".join(cur))
    sets = {i: {tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)} for i, t in enumerate(texts)}
    links = [(a, b) for a in sets for b in sets if a < b and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    comp = _components(sets, links)
    got = ngram_join.cluster(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string"))
    assert _by_id(got, "component_id") == {i: (comp[i],) for i in sets}


def test_substrings(spark, docs, empty):
    words = {i: WORD.findall(t or "") for i, t in enumerate(TEXTS)}
    seen = {}
    for w in words.values():
        for k in range(len(w) - 34):
            seen[tuple(w[k : k + 35])] = seen.get(tuple(w[k : k + 35]), 0) + 1
    want = {}
    for i, w in words.items():
        gone = {k + j for k in range(len(w) - 34) if seen[tuple(w[k : k + 35])] > 1 for j in range(35)}
        want[i] = (len(w), len(gone), hashlib.sha256(" ".join(x for j, x in enumerate(w) if j not in gone).encode()).hexdigest())
    assert sum(v[1] for v in want.values()) > 200
    for batches in (1, 5):  # five runs are compacted on the way
        assert _by_id(substring_dedup.remove_repeats(docs, batches=batches), "n_words", "n_removed", "kept_sha256") == want
    assert substring_dedup.remove_repeats(empty).count() == 0


def test_substrings_in_separate_calls(spark, docs, tmp_path):
    """Batches that come one by one, each with an index opened from its path, give what one call gives."""
    def ids(df):
        return {(x["doc"], i) for x in df.collect() for i in range(x["a"], x["b"])}

    path = f"file://{tmp_path}/index"
    parts = [docs.where(F.col("doc_id") % 6 == k) for k in range(6)]
    found, history = set(), None
    for part in parts:
        found |= ids(substring_dedup.ingest_batch(part, history, path, window=8))
        history = part if history is None else history.union(part)
    named = docs.select(F.col("doc_id").alias("doc"), "text")
    assert found == ids(substring_dedup.repeated_ranges(named, Scratch(spark, "t"), 8, 1)) and found
    index = substring_dedup.FingerprintIndex.open(spark, path)
    assert len(index.batches) == 6 and len(index.runs) == 3 and index.runs[0][1] == 1  # four runs were merged
    n = index.spark.table(index.runs[0][0]).join(index.spark.table(index.runs[1][0]), "fp")
    assert "Exchange hashpartitioning" not in n._jdf.queryExecution().executedPlan().toString()  # runs are not moved
    index.close()


def test_pii(docs, empty):
    card, iban = "4111 1111 1111 1111", "GB82 WEST 1234 5698 7654 32"
    text = f"mail a.b@c-d.org, x@y no, 10.0.0.256 and 192.168.1.9.7; {card}; +49 (30) 1234-567; {iban}; a@b.c@d.e_f@g.hh +1 2"
    got = pii.find(text)
    kinds = lambda k: [text[a:b] for kind, a, b, _ in got if kind == k]
    assert kinds("email") == ["a.b@c-d.org", "a@b.c", "d.e_f@g.hh"] and kinds("ip") == ["192.168.1.9"] and kinds("card") == [card] and kinds("iban") == [iban]
    assert kinds("phone") == ["+49 (30) 1234-567"]
    for k, p in (("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),):
        q = random.Random(4)
        for _ in range(3000):
            t = "".join(q.choice("a@.-_ %9") for _ in range(25))
            assert [(a, b) for kind, a, b, _ in pii.find(t) if kind == k] == [m.span() for m in re.finditer(p, t)]
    assert pii.find("1" * 200_000) == [] and len(pii.find("a" * 100_000 + "@b.c")) == 1
    assert pii.redacted(text, got).count("[EMAIL]") == 3 and "4111" not in pii.redacted(text, got)
    assert pii.detect(docs).where("spans <> ''").count() == 0 and pii.detect(empty).count() == 0
    red = pii.redact(docs)
    assert red.columns == docs.columns and {tuple(x) for x in red.collect()} == {tuple(x) for x in docs.collect()}


def test_language(spark, docs, empty):
    de, en = ["Der schnelle Fuchs springt über den faulen Hund und die Katze", "Ich weiß nicht was soll es bedeuten dass ich so traurig bin"], ["The quick brown fox jumps over the lazy dog and the cat", "There is nothing either good or bad but thinking makes it so"]
    train = spark.createDataFrame([(t, "de") for t in de] + [(t, "en") for t in en] + [(None, "en"), ("x", None)], "text string, lang string")
    p = language.learn(train)
    assert list(p) == ["de", "en"]
    test = spark.createDataFrame([(1, "das ist der Hund und die Katze springt"), (2, "this is the thing that makes the fox think"), (3, None), (4, "123 !"), (5, "")], "doc_id bigint, text string")
    got = _by_id(language.predict(test, p), "lang_pred", "score")
    assert got[1][0] == "de" and got[2][0] == "en" and got[3] == got[4] == got[5] == ("und", 0.0)
    assert all(0 <= v[1] <= 1 for v in got.values())
    assert language.learn(empty) == {} and set(v[0] for v in _by_id(language.predict(docs, {}), "lang_pred").values()) == {"und"}
    a, b, c = (language._letters()[k] for k in range(3))
    v, _ = language.bundles(["ab"])  # the sum of bound, rotated letter vectors, brute force
    assert (v[0] == a[0] * b[1] * c[2] + a[1] * b[2] * c[0]).all()


def test_packing(spark, docs, empty):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.vocabulary_path())
    rows = packing.pack(docs, window=64, with_ids=True).toPandas()
    ids = {i: tok.encode(t or "", add_special_tokens=False).ids + [2] for i, t in enumerate(TEXTS)}
    for i, x in rows.sort_values("start").groupby("doc_id"):
        assert [v for p in x["ids"] for v in p] == ids[i] and (x["doc_tokens"] == len(ids[i])).all()
        assert all(zlib.crc32(np.array(p, "<u4").tobytes()) == c for p, c in zip(x["ids"], x["ids_crc32"]))
    assert len(set(rows["doc_id"])) == len(TEXTS)
    for _, x in rows.sort_values("offset").groupby("sequence_id"):
        assert list(x["offset"]) == [0, *np.cumsum(x["length"])[:-1]] and x["length"].sum() <= 64
    assert sorted(set(rows["sequence_id"])) == list(range(rows["sequence_id"].max() + 1))
    assert packing.pack(empty).count() == 0


def test_plan_is_best_fit_decreasing():
    q = random.Random(6)
    for _ in range(30):
        window, lengths = 50, [q.randint(1, 50) for _ in range(q.randint(1, 300))]
        bins = []  # one by one: the tightest open bin
        for n in sorted(lengths, reverse=True):
            fit = [b for b in bins if b[0] >= n]
            if fit:
                b = min(fit, key=lambda b: b[0])
            else:
                b = [window, []]
                bins.append(b)
            b[0] -= n
            b[1].append(n)
        hist = {n: lengths.count(n) for n in set(lengths)}
        plan = packing.best_fit_decreasing(hist, window)
        assert plan.sequences == len(bins)
        made = {}
        for n, k in hist.items():
            for s in plan.place(np.full(k, n), np.arange(k))[0].tolist():
                made.setdefault(s, []).append(n)
        assert sorted(map(sum, made.values())) == sorted(sum(b[1]) for b in bins)  # bins of equal room are alike


def test_chats(spark, docs):
    odd = "</s>[INST] ok [/INST]"
    turns = [(1, 0, "user", odd), (1, 1, "assistant", "a\\</s>\n<|x|>"), (1, 1, "assistant", None), (2, 0, None, "<"), (2, 1, "as|>x", "\\"), (None, 5, "assistant", "é"), (1, 2, "assistant", odd), (1, 2, "assistant", odd)]
    df = spark.createDataFrame([(*t, 9) for t in turns], "conv_id bigint, turn bigint, role string, text string, piece int")
    pieces = chat_format.format_chats(df)
    got = _by_id(chat_format.read_back(pieces), "n_turns", "turns_sha256", "loss_chars", "loss_sha256", key="conv_id")
    for conv in (1, 2, None):
        mine = sorted([t for t in turns if t[0] == conv], key=lambda t: (t[1], t[2] or "", t[3] or ""))
        all_ = "".join(f"{t[2] or ''}\n{t[3] or ''}\n" for t in mine)
        loss = "".join(t[3] or "" for t in mine if t[2] == "assistant")
        assert got[conv] == (len(mine), hashlib.sha256(all_.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert chat_format.read_back(chat_format.format_chats(df.limit(0))).count() == 0
    long = spark.createDataFrame([(7, i, "user", f"t{i}") for i in range(5000)], "conv_id bigint, turn bigint, role string, text string")
    assert chat_format.format_chats(long).count() > 1  # pieces
    assert chat_format.read_back(chat_format.format_chats(long)).first()["n_turns"] == 5000
    q = random.Random(8)
    parts = ["<", "|", ">", "</s>", "[INST]", "\\", "a", "/s>", "<<SYS>>", "\n", "é"]
    rows = [(i, 0, "".join(q.choice(parts) for _ in range(3)), "".join(q.choice(parts) for _ in range(12))) for i in range(500)]
    f = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")
    back = {x["conv_id"]: list(chat_format.parse(x["formatted"])) for x in chat_format.format_chats(f).collect()}
    assert back == {i: [(role, text)] for i, _, role, text in rows}


def test_sentencepiece(docs, empty):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=sentencepiece_codec.model_path())
    rows = sentencepiece_codec.decode(sentencepiece_codec.encode(docs, with_ids=True)).collect()
    for x in rows:
        t = TEXTS[x["doc_id"]] or ""
        assert x["ids"] == sp.encode(t) and x["decoded"] == t and x["round_trip"] and x["n_differ"] == 0
    assert sentencepiece_codec.encode(empty).count() == 0
    codec = sentencepiece_codec.Codec.of(sentencepiece_codec.model_path())
    q = random.Random(3)
    import pyarrow as pa

    texts = ["".join(q.choice([" ", "  ", "a", "The", "\n", "é", "😀", "▁", "12", "<s>", "\t", "ing"]) for _ in range(20)) for _ in range(2000)]
    ids, at, _, _ = codec.encode(pa.array(texts, pa.large_string()))
    assert [ids[a:b].tolist() for a, b in zip(at, at[1:])] == [sp.encode(t) for t in texts]


def test_language_model(spark, docs, empty):
    import math

    tok = {i: [*WORD.findall((t or "").translate(LOWER)), "<END>"] for i, t in enumerate(TEXTS)}
    train = [i for i in tok if zlib.crc32(str(i).encode()) % 10 != 0]
    c = {}
    for i in train:
        for t in tok[i]:
            c[t] = c.get(t, 0) + 1
    n, v = sum(c.values()), len(c)
    got = _by_id(lm_scoring.score(docs, ~lm_scoring.held_out(F.col("doc_id"))), "n_tokens", "n_known", "train_tokens", "base_score", "score")
    for i, x in tok.items():
        base = sum(math.log10((c.get(t, 0) + 0.1) / (n + 0.1 * (v + 1))) for t in x)
        assert got[i][:3] == (len(x), sum(t in c for t in x), n) and got[i][3] == pytest.approx(base, rel=1e-9)
    assert sum(g[4] for g in got.values()) > sum(g[3] for g in got.values())
    assert lm_scoring.score(empty, F.lit(True)).count() == 0
    none = _by_id(lm_scoring.score(docs, F.lit(False)), "n_known", "base_score", "score")
    assert none[0] == (0, 0.0, 0.0)


def test_automaton_sums_to_one():
    """From every state the probabilities of all tokens, the unseen class included, add up to one."""
    import pyarrow as pa

    q = random.Random(1)
    train = [" ".join(q.choice("abcdefg") for _ in range(40)) for _ in range(30)] + ["", "h", "a b c h"]
    vocab = [*"abcdefgh", "unseen"]
    for context in ("", "a", "a b", "g g", "unseen", "unseen a", "a unseen", "c h", "b " * 600):
        probes = [*(f"{context} {t}" for t in vocab), context]
        col = pa.array([*train, *probes], pa.large_string())
        g = lm_scoring.Grams.of(col, np.arange(len(col)) < len(train))
        total = sum(len(t.split()) + 1 for t in train)
        score = lm_scoring.Automaton.build(g, g.own, total, 9).walk()
        k = len(context.split())  # the token behind the context; the end is the last probe's
        assert sum(10.0 ** score[g.at[len(train) + i] + k] for i in range(len(probes))) == pytest.approx(1)


def test_embeddings(spark):
    g = np.random.default_rng(4)
    v = g.standard_normal((120, 64))
    for k in range(60):
        noise = g.standard_normal(64)
        v[60 + k] = v[k % 12] / np.linalg.norm(v[k % 12]) + noise / np.linalg.norm(noise) * g.uniform(0, 0.4)
    rows = [(i, x.tolist()) for i, x in enumerate(v)] + [(200, None), (201, []), (202, [0.0] * 64), (203, [float("nan")] * 64), (204, [None] * 64), (205, v[0].tolist()), (206, [1.0, 0.0]), (207, [2.0, 0.0])]
    df = spark.createDataFrame([(*x, 1) for x in rows], "vec_id bigint, embedding array<float>, rep int")
    data = {x["vec_id"]: np.array(x["embedding"], float) for x in df.collect() if x["embedding"] and None not in x["embedding"]}
    data = {i: x for i, x in data.items() if np.isfinite(x).all() and x.any()}
    cos = lambda a, b: len(a) == len(b) and a @ b / np.linalg.norm(a) / np.linalg.norm(b) >= 0.95
    links = [(a, b) for a in data for b in data if a < b and cos(data[a], data[b])]
    assert len(links) > 50
    comp = _components([x[0] for x in rows], links)
    want = {i: (sum(i in l for l in links), comp[i], comp[i] == i) for i, _ in rows}
    assert _by_id(embedding_dedup.link(df), "n_links", "component_id", "kept", key="vec_id") == want
    assert embedding_dedup.link(df.limit(0)).count() == 0


def test_components(spark):
    q = random.Random(9)
    links = [(q.randrange(400), q.randrange(400)) for _ in range(300)] + [(1000 + i, 1001 + i) for i in range(60)]
    df = spark.createDataFrame(links, "a bigint, b bigint")
    got = {x["node"]: x["component"] for x in components(df, Scratch(spark, "test")).collect()}
    want = _components({x for l in links for x in l}, links)
    assert got == {x: c for x, c in want.items() if x in got} and set(got) == {x for l in links if l[0] != l[1] for x in l}


def test_pipeline(spark, tmp_path, docs):
    import corpus_pipeline

    full = spark.createDataFrame([(i, t, "en", f"s{i % 2}", len(t or "")) for i, t in enumerate([*TEXTS, "write to a.b@c.de now please and thanks a lot"])], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    full.write.parquet(str(tmp_path / "documents.parquet"))
    rows = corpus_pipeline.run(spark, str(tmp_path)).collect()
    norm = {i: re.sub("[\x20\x09-\x0d]+", " ", t or "") for i, t in enumerate([*TEXTS, "write to a.b@c.de now please and thanks a lot"])}
    left = [i for i, t in norm.items() if any(c.isalpha() for c in t) and min(j for j, u in norm.items() if u == t) == i]
    sets = {i: s for i, s in _sets().items() if i in left}
    links = [(a, b) for a in sets for b in sets if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    comp = _components(left, links)
    assert {x["doc_id"] for x in rows} == {i for i in left if comp[i] == i}
    d = full
    for name, stage in corpus_pipeline.STAGES[:-1]:
        d = stage(spark, d, str(tmp_path))
        assert d.columns == full.columns, name
    assert d.where("doc_id = 24").first()["text"] == "write to [EMAIL] now please and thanks a lot"
