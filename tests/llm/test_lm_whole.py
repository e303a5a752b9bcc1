"""Every n-gram that occurs twice counts, however large the corpus is."""

import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from semjoin.llm import lm_scoring


def _expected(train, probes, K=lm_scoring.STRENGTH):
    """The model by its definition, in dictionaries."""
    START, END = "<START>", "<END>"
    docs = [[*t.split(), END] for t in train]
    c1 = Counter(t for d in docs for t in d)
    c2 = Counter(p for d in docs for p in zip([START, *d], d))
    c3 = Counter(g for d in docs for g in zip([START, *d], d, d[1:]))
    n, types = sum(c1.values()), len(c1)
    context = Counter({START: len(docs)}) + c1

    def p1(t):
        return (c1[t] + 0.1) / (n + 0.1 * (types + 1))

    def p2(v, t):
        return (c2[v, t] + K * p1(t)) / (context[v] + K)

    def p3(u, v, t):
        return (c3[u, v, t] + K * p2(v, t)) / (c2[u, v] + K)

    out = []
    for text in probes:
        d = [*text.split(), END]
        out.append(math.log10(p2(START, d[0])) + sum(math.log10(p3(u, v, t)) for u, v, t in zip([START, *d], d, d[1:])))
    return out, c2, n


@pytest.mark.parametrize("size, block, keys", [(20_000, lm_scoring.BLOCK_BYTES, lm_scoring.PART_KEYS), (300, 3000, 500)])
def test_rare_ngrams_count(spark, monkeypatch, size, block, keys):
    """With 800,000 tokens a floor of 4e-6 of them would drop what occurs two or three times; small blocks and ranges change nothing."""
    monkeypatch.setattr(lm_scoring, "BLOCK_BYTES", block)
    monkeypatch.setattr(lm_scoring, "PART_KEYS", keys)
    g = np.random.default_rng(3)
    vocab = np.array([f"w{i}" for i in range(1500)])
    draw = lambda k: " ".join(vocab[np.minimum(g.zipf(1.3, k), 1500) - 1])
    train = [draw(size) for _ in range(40)] + ["alpha beta gamma delta"] * 2
    probes = ["alpha beta gamma delta", "beta gamma", "never seen", "", draw(700), train[0][:3000], "alpha"]
    want, c2, n = _expected(train, probes)
    assert c2["alpha", "beta"] == 2 and (size < 1000 or n * 4e-6 > 3)
    df = spark.createDataFrame([(i, t) for i, t in enumerate([*train, *probes])], "doc_id bigint, text string").repartition(4)
    got = {x["doc_id"]: x["score"] for x in lm_scoring.score(df, F.col("doc_id") < len(train)).collect()}
    assert [got[len(train) + i] for i in range(len(probes))] == pytest.approx(want, rel=1e-6)
