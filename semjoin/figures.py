"""The measured experiments in full: all operators on the three workloads, the informed join, switches.

Their SQL plays the runs call by call: it plans batches as the planner does, cuts the tables in order of ids,
counts what each cell reads and writes, and stops a wave at the first answer that is cut off.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semjoin import queries as q
from semjoin import workloads
from semjoin.functions import costs
from semjoin.lm.base import Latency
from semjoin.operators import embedding, joins, quality
from semjoin.plans import simulate
from semjoin.prompts import PromptStyle
from semjoin.state import Scratch

CONTEXT = 2000  # tokens of a call, as in the measured experiments
START, GROWTH, ROUNDS = 0.0001, 4, 8  # 0.0001 * 4^7 exceeds 1
METHODS = ("pairwise", "block", "informed", "adaptive", "embedding", "parallel_pairwise")
PUBLISHED = ("pairwise", "block", "adaptive", "embedding", "parallel_pairwise")  # the five of the published figures
_LATENCY = Latency()


def _runs_sql(w: str) -> str:
    """(method, calls, tokens_read, tokens_written, latency_ms) of every method on a workload."""
    pred, style = q._SHAPES[w]
    p, pair, verbose, over = style.instruction_tokens(pred.text), style.instruction_tokens(pred.text, "pair"), PromptStyle(verbose=True).instruction_tokens(pred.text, "pair"), style.row_overhead
    t, width, ratio = CONTEXT - p - 1, joins.WIDTH_MATCH, 2
    return f"""
        WITH {q._WITH[w]},
        l AS (SELECT id, row_number() OVER (ORDER BY id) - 1 AS i, {q._words('text')} AS w FROM lhs),
        r AS (SELECT id, row_number() OVER (ORDER BY id) - 1 AS i, {q._words('text')} AS w FROM rhs),
        z AS (SELECT (SELECT count(*) FROM l) AS n, (SELECT count(*) FROM r) AS m, (SELECT sum(w) FROM l) AS wl, (SELECT sum(w) FROM r) AS wr,
                     (SELECT avg(w) FROM l) + {over} AS w1, (SELECT avg(w) FROM r) + {over} AS w2,
                     (SELECT max(w) FROM l) + {over} AS x1, (SELECT max(w) FROM r) + {over} AS x2, (SELECT count(*) FROM truth) AS t),
        e AS (SELECT 'block' AS method, 0 AS k, 1.0::DOUBLE AS e UNION ALL SELECT 'informed', 0, t::DOUBLE / (n * m) FROM z
              UNION ALL SELECT 'adaptive', k, least(1.0::DOUBLE, {START}::DOUBLE * pow({GROWTH}, k)) FROM range(0, {ROUNDS}) x(k)
              UNION ALL SELECT 'adaptive', {ROUNDS}, 1.0::DOUBLE), -- the last one is planned for the widest rows
        ez AS (SELECT method, k, e, n, m, CASE WHEN k = {ROUNDS} THEN x1 ELSE w1 END AS w1, CASE WHEN k = {ROUNDS} THEN x2 ELSE w2 END AS w2 FROM e, z),
        o AS (SELECT method, k, n, m, w1, w2, x, least(m, floor(({t} - x * w1) / (w2 + x * {width} * e) + 1e-9)) AS y FROM ez, range(1, {CONTEXT}) s(x) WHERE x <= least(n, floor({t} / w1))),
        o2 AS (SELECT *, ceil(n / ceil(n::DOUBLE / x)) AS a, ceil(m / ceil(m::DOUBLE / y)) AS b FROM o WHERE y >= 1),
        o3 AS (SELECT *, ceil(n::DOUBLE / a) AS nl, ceil(m::DOUBLE / b) AS nr FROM o2),
        o4 AS (SELECT *, nl * nr * {p} + nr * n * w1 + nl * m * w2 AS cost FROM o3),
        plans AS (SELECT method, k, arg_min(a, (cost, a * b, a, b))::BIGINT AS a, arg_min(b, (cost, a * b, a, b))::BIGINT AS b, arg_min(nl, (cost, a * b, a, b))::BIGINT AS nl, arg_min(nr, (cost, a * b, a, b))::BIGINT AS nr FROM o4 GROUP BY method, k),
        lb AS (SELECT method, k, i // a AS lb, sum(w + {over}) AS w FROM plans, l GROUP BY 1, 2, 3), rb AS (SELECT method, k, i // b AS rb, sum(w + {over}) AS w FROM plans, r GROUP BY 1, 2, 3),
        hits AS (SELECT method, k, l.i // a AS lb, r.i // b AS rb, count(*) AS c FROM plans, truth JOIN l ON l.id = left_id JOIN r ON r.id = right_id GROUP BY 1, 2, 3, 4),
        cells AS (SELECT method, k, lb, rb, {p} + lb.w + rb.w AS rd, 4 * coalesce(c, 0) + 1 AS need FROM lb JOIN rb USING (method, k) LEFT JOIN hits USING (method, k, lb, rb)),
        step AS (SELECT method, k, nr, nl * nr AS cells, (SELECT min(s) FROM range(1, 1000000) u(s) WHERE s >= greatest(1, floor(nl * nr * 0.6180339887)) AND gcd(s, nl * nr) = 1) AS s FROM plans),
        placed AS (SELECT c.*, (lb * nr + rb) * s % cells AS rank, need > greatest(0, {CONTEXT} - rd) AS cut, least(need, greatest(0, {CONTEXT} - rd)) AS wr FROM cells c JOIN step USING (method, k)),
        waved AS (SELECT *, CASE WHEN method <> 'adaptive' OR rank >= {joins.PROBES} THEN 9 WHEN rank < 1 THEN 1 WHEN rank < 3 THEN 2 ELSE 3 END AS wave FROM placed),
        ends AS (SELECT method, k, min(wave) FILTER (WHERE cut) AS wave FROM waved GROUP BY 1, 2),
        done AS (SELECT method, min(k) FILTER (WHERE wave IS NULL OR method <> 'adaptive') AS k FROM ends GROUP BY 1),
        paid AS (SELECT x.method, rd, wr FROM waved x JOIN ends y USING (method, k) JOIN done d USING (method) WHERE x.k <= d.k AND x.wave <= coalesce(y.wave, 9)),
        runs AS (SELECT method, count(*) AS calls, sum(rd) AS rd, sum(wr) AS wr FROM paid GROUP BY 1
                 UNION ALL SELECT 'pairwise', n * m, n * m * {pair} + m * wl + n * wr, n * m FROM z
                 UNION ALL SELECT 'parallel_pairwise', n * m, n * m * {verbose} + m * wl + n * wr, 3 * n * m FROM z
                 UNION ALL SELECT 'embedding', 1, wl + wr, 0 FROM z)
        SELECT '{w}' AS workload, method, calls::BIGINT AS calls, rd::BIGINT AS tokens_read, wr::BIGINT AS tokens_written,
               CASE WHEN method = 'embedding' THEN 0 ELSE round(calls * {_LATENCY.fixed} + rd * {_LATENCY.read} + wr * {_LATENCY.write}, 3) END::DOUBLE AS latency_ms FROM runs"""


def _run(x: workloads.Workload, method: str):
    m = q._model(x, CONTEXT)
    if method == "pairwise":
        return joins.pairwise_join(x.left, x.right, x.predicate, m)
    if method == "parallel_pairwise":
        return joins.parallel_pairwise_engine(x.left, x.right, x.predicate, m)
    if method == "embedding":
        return embedding.embedding_join(x.left, x.right, embedding.HashingEmbedder(64))
    if method == "adaptive":
        return joins.adaptive_join(x.left, x.right, x.predicate, m, START, GROWTH, order="key")
    sigma = 1.0
    if method == "informed":
        sigma = x.truth.count() / (x.left.count() * x.right.count())
    return joins.block_join_planned(x.left, x.right, x.predicate, m, sigma, order="key", on_overflow="report")


def runs(spark, d: str, methods=METHODS) -> DataFrame:
    """Usage of the methods on every workload, from the ledgers of runs made for it, and the engine's own seconds."""
    out = []
    for w in q._WITH:
        x = q._make(w, spark, d)
        for m in methods:
            run = _run(x, m)
            out.append(run.usage().select(F.lit(w).alias("workload"), F.lit(m).alias("method"), "calls", "tokens_read", "tokens_written", F.round("latency_ms", 3).alias("latency_ms"), F.lit(round(run.seconds, 3)).alias("seconds")))
    return Scratch(spark, "figures").table(joins._union(out), "runs")


def _all(methods=METHODS) -> str:
    return "(" + " UNION ALL ".join(f"SELECT * FROM ({_runs_sql(w)})" for w in q._WITH) + ") x WHERE method IN (" + ", ".join(f"'{m}'" for m in methods) + ")"


def _fee() -> Column:
    return F.round(q._fee().cast("double"), 6)


_FEE = f"round({q._FEE_SQL}::DOUBLE, 6)"


@q.query("operators_usage", f"SELECT workload, method, calls, tokens_read, tokens_written FROM {_all()}")
def operators_usage(spark, d):
    return runs(spark, d).drop("latency_ms", "seconds")


@q.query("operators_fees", f"SELECT workload, method, {_FEE} AS fee FROM {_all(PUBLISHED)}")
def operators_fees(spark, d):
    return runs(spark, d, PUBLISHED).select("workload", "method", _fee().alias("fee"))


@q.query("operators_latency", f"SELECT workload, method, latency_ms FROM {_all(PUBLISHED)}")
def operators_latency(spark, d):
    """What the calls would take one after the other."""
    return runs(spark, d, PUBLISHED).select("workload", "method", "latency_ms")


@q.query("operators_seconds")
def operators_seconds(spark, d):
    """Wall seconds of this engine beside the modelled seconds of its calls."""
    return runs(spark, d, PUBLISHED).select("workload", "method", "seconds", F.round(F.col("latency_ms") / 1000, 3).alias("modelled_seconds"))


@q.query("operators_ratios", f"WITH x AS (SELECT workload, method, {_FEE} AS fee FROM {_all(('pairwise', 'block', 'informed', 'adaptive'))}) SELECT m.workload, b.method AS baseline, round(b.fee / m.fee, 6) AS ratio FROM x m JOIN x b USING (workload) WHERE m.method = 'adaptive' AND b.method <> 'adaptive'")
def operators_ratios(spark, d):
    """How many times the adaptive join's fee the others' are; over the informed join it is the inverse of its regret."""
    fees = runs(spark, d, ("pairwise", "block", "informed", "adaptive")).select("workload", "method", _fee().alias("fee"))
    some = [quality.compare(fees, "adaptive", b).select("workload", F.lit(b).alias("baseline"), F.round("ratio", 6).alias("ratio")) for b in ("pairwise", "block", "informed")]
    return joins._union(some)


@q.query("adaptive_regret", f"WITH x AS (SELECT workload, method, {_FEE} AS fee FROM {_all(('informed', 'adaptive'))}) SELECT a.workload, round(a.fee / i.fee, 6) AS regret, {float(GROWTH * 2)}::DOUBLE AS bound FROM x a JOIN x i USING (workload) WHERE a.method = 'adaptive' AND i.method = 'informed'")
def adaptive_regret(spark, d):
    fees = runs(spark, d, ("informed", "adaptive")).select("workload", "method", _fee().alias("fee"))
    return quality.compare(fees, "informed", "adaptive").select("workload", F.round("ratio", 6).alias("regret"), F.lit(costs.regret_bound(GROWTH, 2.0)).alias("bound"))


query_methods = ("pairwise", "block", "informed", "adaptive", "parallel_pairwise")


@q.query("operators_quality", " UNION ALL ".join(q._QUALITY(w).replace(str(list(q._METHODS)), str(list(query_methods))) for w in q._WITH))
def operators_quality(spark, d):
    """With one seeded noise for all of them; what noise does to a pair doesn't depend on its prompt."""
    out = []
    for w in q._WITH:
        x = q._make(w, spark, d)
        m = q.NoisyModel(x.predicate, q.ModelProfile(), miss=q.MISS, false_alarm=q.ALARM, seed=q.SEED)
        for method in query_methods:
            if method == "pairwise":
                run = joins.pairwise_join(x.left, x.right, x.predicate, m)
            elif method == "parallel_pairwise":
                run = joins.parallel_pairwise_engine(x.left, x.right, x.predicate, m)
            elif method == "adaptive":
                run = joins.adaptive_join(x.left, x.right, x.predicate, m, 0.001)
            else:
                sigma = 1.0 if method == "block" else x.truth.count() / (x.left.count() * x.right.count())
                run = joins.adaptive_join(x.left, x.right, x.predicate, m, min(1.0, 4 * sigma), probe="none", restart="failed")
            out.append(_measures(w, method, run.quality(x.truth)))
    return joins._union(out)


def _measures(w: str, method: str, measured: DataFrame) -> DataFrame:
    return measured.select(F.lit(w).alias("workload"), F.lit(method).alias("method"), *[F.round(x, 6).alias(x) for x in ("recall", "precision", "f1")])


@q.query("embedding_quality")
def embedding_quality(spark, d):
    """The fifth operator: right where likeness is the condition (offers), wrong where it isn't (contradiction, sentiment)."""
    out = []
    for w in q._WITH:
        x = q._make(w, spark, d)
        out.append(_measures(w, "embedding", embedding.embedding_join(x.left, x.right, embedding.HashingEmbedder()).quality(x.truth)))
    return joins._union(out)


# ---- switches ----

_SWITCHES = {
    "as it is": {}, "no nudge": {"style": PromptStyle(nudge=False)}, "rows as answers": {"style": PromptStyle(answer_form="rows")},
    "restart failed": {"restart": "failed"}, "no probe": {"probe": "none"}, "downward": {"direction": "down", "start_estimate": 1.0},
}


@q.query("adaptive_switches")
def adaptive_switches(spark, d):
    """Calls, tokens and fee of the adaptive join with one switch changed at a time; all find the same pairs."""
    x = q._make("sentiment", spark, d)
    m = q._model(x, CONTEXT)
    out = []
    for name, options in _SWITCHES.items():
        run = joins.adaptive_join(x.left, x.right, x.predicate, m, **({"start_estimate": 0.001, "order": "key"} | options))
        u = run.usage().select(F.lit(name).alias("switch"), "calls", "tokens_read", "tokens_written", F.lit(len(run.rounds)).alias("rounds"), F.lit("chat").alias("method"))
        out.append(u.withColumn("fee", _fee()).drop("method").crossJoin(run.pairs.agg(F.count("*").alias("pairs"))))
    return Scratch(spark, "switches").table(joins._union(out), "runs")


_ENDS = "ceil(50 / a) * ceil(10 / b) * 1 + ceil(10 / b) * 50 * 10 + ceil(50 / a) * 10 * 2 + 500 * sigma"


@q.query("clamp_switch", f"""WITH s AS (SELECT DISTINCT l_discount AS sigma FROM lineitem WHERE l_discount IS NOT NULL),
    clamped AS (SELECT sigma, min({_ENDS}) AS cost FROM s, (SELECT unnest(range(1, 51))::DOUBLE AS a), (SELECT unnest(range(1, 11))::DOUBLE AS b) WHERE a * 10 + b * 2 + a * b * sigma <= 100 GROUP BY 1),
    x AS (SELECT sigma, unnest([greatest(1, floor({q._LEFT})), greatest(1, ceil({q._LEFT}))]) AS a FROM s),
    y AS (SELECT *, floor((100 - a * 10) / (2 + a * sigma) + 1e-9) AS b FROM x),
    z AS (SELECT sigma, arg_min(a, (c, a * b, a, b)) AS a, arg_min(b, (c, a * b, a, b)) AS b FROM (SELECT *, (50 / a) * (10 / b) * (1 + a * 10 + b * 2 + a * b * sigma) AS c FROM y WHERE b >= 1) GROUP BY 1),
    published AS (SELECT sigma, {_ENDS} AS cost FROM (SELECT sigma, least(50, a) AS a, least(10, b) AS b FROM z))
    SELECT sigma, round(c.cost, 6) AS clamped, round(p.cost, 6) AS published FROM clamped c JOIN published p USING (sigma)""")
def clamp_switch(spark, d):
    """Totals of whole sizes that end with the table and of the published rounding, both with ragged last batches.

    The estimates are the discounts of lineitem.
    """
    from semjoin.plans.optimize import optimal_batches

    rows = []
    discounts = q.load(spark, d, "lineitem").where("l_discount is not null").select("l_discount").distinct()
    for s in sorted(x["l_discount"] for x in discounts.collect()):
        a, b = (optimal_batches(*q._SMALL, s, 100, 1, 1, 1.0, clamp=c) for c in (True, False))
        rows.append((s, *(round(costs.ragged_cost(50, 10, min(50, x.batch_left), min(10, x.batch_right), 1, 10, 2, 1, s, 1), 6) for x in (a, b))))
    return spark.createDataFrame(rows, "sigma double, clamped double, published double")


def _growth_sql() -> str:
    return """
        WITH g AS (SELECT DISTINCT 1.0::DOUBLE + l_linenumber AS growth FROM lineitem WHERE l_linenumber IS NOT NULL),
        e AS (SELECT growth, k, 0.00001::DOUBLE * pow(growth, k) AS e FROM g, range(0, 14) x(k)),
        s AS (SELECT *, greatest(1, least(5000, floor(30 * 8142 / (sqrt(900.0::DOUBLE * 900 + 900 * 2 * e * 8142) + 900) + 1e-9))) AS a FROM e WHERE e < 1),
        b AS (SELECT *, greatest(1, least(5000, floor((8142 - a * 30) / (30 + a * 2 * e) + 1e-9))) AS b FROM s),
        o AS (SELECT *, 8142 - a * 30 - b * 30 AS room, a * b * 0.001 * 2 > 8142 - a * 30 - b * 30 + 1e-9 AS bad FROM b),
        last AS (SELECT growth, min(k) FILTER (WHERE NOT bad) AS k FROM o GROUP BY 1),
        f AS (SELECT growth, sum(CASE WHEN o.k < last.k THEN ((50 + a * 30 + b * 30) * 0.03 + least(room, a * b * 0.001 * 2) * 0.06) / 1000
                     ELSE ((ceil(5000 / a) * ceil(5000 / b) * 50 + ceil(5000 / b) * 5000 * 30 + ceil(5000 / a) * 5000 * 30) * 0.03 + 50000 * 0.06) / 1000 END) AS fee FROM o JOIN last USING (growth) WHERE o.k <= last.k GROUP BY 1)
        SELECT growth, last.k::INT AS void_calls, round(fee, 2) AS fee FROM f JOIN last USING (growth)"""


@q.query("growth_ablation", _growth_sql())
def growth_ablation(spark, d):
    """Growth factors of 2 and more: a step for each line number of lineitem."""
    numbers = q.load(spark, d, "lineitem").where("l_linenumber is not null").select("l_linenumber").distinct()
    settings = [(g, replace(simulate.Setting(), growth=g)) for g in sorted(1.0 + x["l_linenumber"] for x in numbers.collect())]
    fees = {x["x"]: x["fee"] for x in simulate.simulate(spark, settings, ("adaptive",)).collect()}
    rows = [(g, len(simulate.void_calls(s)[0]), fees[g]) for g, s in settings]
    return spark.createDataFrame(rows, "growth double, void_calls int, fee double")


_REAL = ("part", "orders", "customer", "lineitem")


@q.query("sweep_real_rows", f"""WITH s AS ({" UNION ALL ".join(f"SELECT '{t}' AS name, count(*)::DOUBLE AS r1 FROM {t}" for t in _REAL)}),
    e AS (SELECT *, 'block' AS method, 1.0::DOUBLE AS e FROM s UNION ALL SELECT *, 'informed', 0.001::DOUBLE FROM s),
    a AS (SELECT *, greatest(1, least(r1, floor(30 * 8142 / (sqrt(900.0::DOUBLE * 900 + 900 * 2 * e * 8142) + 900) + 1e-9))) AS na FROM e),
    b AS (SELECT *, greatest(1, least(5000, floor((8142 - na * 30) / (30 + na * 2 * e) + 1e-9))) AS nb FROM a)
    SELECT name, r1::BIGINT AS rows_left, method, round(((ceil(r1 / na) * ceil(5000 / nb) * 50 + ceil(5000 / nb) * r1 * 30 + ceil(r1 / na) * 5000 * 30) * 0.03 + r1 * 5000 * 0.001 * 2 * 0.06) / 1000, 2) AS fee FROM b""")
def sweep_real_rows(spark, d):
    """The sweep over left rows at the real sizes of the given tables."""
    counts = [(t, q.load(spark, d, t).count()) for t in _REAL]
    out = []
    for name, n in counts:
        got = simulate.simulate(spark, [(0.0, replace(simulate.Setting(), rows_left=n))], ("conservative", "informed"))
        out.append(got.select(F.lit(name).alias("name"), F.lit(n).cast("long").alias("rows_left"), F.when(F.col("method") == "conservative", "block").otherwise(F.col("method")).alias("method"), "fee"))
    return joins._union(out)
