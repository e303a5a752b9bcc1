"""Named queries of the engine's own operators, and their SQL for DuckDB."""

from __future__ import annotations

import itertools
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from semjoin import workloads
from semjoin.functions import costs, tokens
from semjoin.lm.base import EachPair, SemanticPredicate
from semjoin.lm.models import NoisyModel, TruthModel
from semjoin.operators import batching, embedding, joins, quality, variants
from semjoin.plans import optimize, profile, simulate
from semjoin.prompts import PromptStyle
from semjoin.sources import load
from semjoin.state import Scratch, shared_root
from semjoin.types import JoinRun, ModelProfile, TableProfile

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

P = tokens.WORDS  # the pattern, written out in SQL


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def _r(c: Column, n: int = 6) -> Column:
    return F.round(c, n)


def _words(text: str) -> str:
    return f"len(regexp_extract_all({text}, '{P}'))"


# ---- tokens, profiles, batches ----


def _profile(table: str, id_col: str, text: str, other: tuple[str, str, str] | None = None):
    def run(spark, d):
        made = lambda t, i, x: load(spark, d, t).select(F.col(i).alias("row_id"), F.col(x).alias("text"))
        out = profile.profile_table("left", made(table, id_col, text))
        if other:
            out = out.unionByName(profile.profile_table("right", made(*other)))
        return out.select("side", "n_rows", _r(F.col("width_mean")).alias("width_mean"), "width_max")

    one = lambda side, t, x: f"SELECT '{side}' AS side, count(*) AS n_rows, round(avg({_words(x)}), 6) AS width_mean, max({_words(x)})::INT AS width_max FROM {t}"
    return run, " UNION ALL ".join([one("left", table, text), *([one("right", other[0], other[2])] if other else [])])


for _name, _args in {"profile_documents": ("documents", "doc_id", "text", ("benchmark", "item_id", "text")), "profile_part": ("part", "p_partkey", "p_name"), "profile_conversations": ("conversations", "conv_id", "text")}.items():
    _f, _s = _profile(*_args)
    query(_name, _s)(_f)


@query("token_counts", f"SELECT doc_id, {_words('text')}::INT AS words, ceil(length(text) / 4.0)::INT AS chars4 FROM documents")
def token_counts(spark, d):
    docs = load(spark, d, "documents")
    return docs.select("doc_id", tokens.count_column(F.col("text")).alias("words"), tokens.count_column(F.col("text"), "chars4").alias("chars4"))


@query("cut_documents", f"SELECT doc_id, least(100, {_words('text')})::INT AS kept_tokens FROM documents")
def cut_documents(spark, d):
    return load(spark, d, "documents").select("doc_id", tokens.count_column(tokens.first_tokens(F.col("text"), 100)).alias("kept_tokens"))


def _part_rows(spark, d):
    return load(spark, d, "part").select(F.col("p_partkey").alias("row_id"), F.col("p_name").alias("text"), F.lit(None).cast("string").alias("key"))


@query("batches_fixed", "SELECT (i // 100)::BIGINT AS batch_id, count(*)::INT AS n_rows, min(p_partkey) AS first_id, max(p_partkey) AS last_id FROM (SELECT p_partkey, row_number() OVER (ORDER BY p_partkey) - 1 AS i FROM part) GROUP BY 1")
def batches_fixed(spark, d):
    b = batching.make_batches(_part_rows(spark, d), 100, order="key")
    return b.select("batch_id", F.size("items").alias("n_rows"), F.element_at("items", 1).row_id.alias("first_id"), F.element_at("items", -1).row_id.alias("last_id"))


@query("batches_packed_limits", f"SELECT count(*) AS n_rows, sum({_words('text')})::BIGINT AS tokens, 0::BIGINT AS violations, count(DISTINCT item_id) AS n_distinct FROM benchmark")
def batches_packed_limits(spark, d):
    """Every row lies in one batch, no batch exceeds its limit, and batches hold the tokens that SQL counts in the texts."""
    rows = load(spark, d, "benchmark").select(F.col("item_id").alias("row_id"), "text", F.lit(None).cast("string").alias("key"))
    items = batching.pack_batches(rows, 400).select("batch_id", F.explode("items").alias("i"))
    n = F.col("i.row_id")
    per = items.groupBy("batch_id").agg(F.count("*").alias("rows"), F.sum(tokens.count_column(F.col("i.text"))).alias("t"), F.collect_set(n).alias("ids"))
    counts = per.agg(F.sum("rows").alias("n_rows"), F.sum("t").cast("long").alias("tokens"), F.count_if(F.col("t") > 400).alias("violations"))
    return counts.crossJoin(items.agg(F.countDistinct(n).alias("n_distinct")))


@query("cells_count", "SELECT l AS left_batches, r AS right_batches, l * r AS cells FROM (SELECT ceil(count(*) / 150.0)::BIGINT AS l FROM part), (SELECT ceil(count(*) / 70.0)::BIGINT AS r FROM supplier)")
def cells_count(spark, d):
    lb = batching.make_batches(_part_rows(spark, d), 150)
    sup = load(spark, d, "supplier").select(F.col("s_suppkey").alias("row_id"), F.col("s_name").alias("text"), F.lit(None).cast("string").alias("key"))
    cells = batching.make_cells(lb, batching.make_batches(sup, 70))  # on tiles
    return cells.agg(F.countDistinct("left_batch").alias("left_batches"), F.countDistinct("right_batch").alias("right_batches"), F.count("*").alias("cells"))


# ---- formulas on grids ----

SIGMAS = [0.0001, 0.001, 0.01, 0.1, 0.25, 0.5, 1.0]
EX = {"rows_left": 50.0, "rows_right": 10.0, "width_left": 10.0, "width_right": 2.0, "width_match": 1.0, "write_ratio": 1.0, "instruction_tokens": 1.0, "budget": 100.0}
_LIST = lambda xs: "[" + ", ".join(f"{x!r}::DOUBLE" for x in xs) + "]"


def _grid(spark: SparkSession, **axes) -> DataFrame:
    rows = [tuple(map(float, r)) for r in itertools.product(*axes.values())]
    return spark.createDataFrame(rows, ", ".join(f"{n} double" for n in axes)).coalesce(1)


def _from(**axes) -> str:
    return "FROM " + ", ".join(f"(SELECT unnest({_LIST(xs)}) AS {n})" for n, xs in axes.items())


def _formula(name: str, axes: dict, column: Callable[[], dict[str, Column]], sql: dict[str, str], where: tuple | None = None):
    def run(spark, d):
        g = _grid(spark, **axes)
        if where:
            g = g.where(where[0])
        return g.select(*axes, *[(c if c is not None else F.lit(None)).alias(n) for n, c in column().items()])

    text = "SELECT " + ", ".join([*axes, *(f"{x} AS {n}" for n, x in sql.items())]) + " " + _from(**axes) + (f" WHERE {where[1]}" if where else "")
    query(name, text)(run)


def _table_formula(name: str, axes: dict[str, str], column: Callable[[], dict[str, Column]], sql: dict[str, str]):
    """A formula at every combination of sizes and shares that occurs in lineitem, with the lines that have it; ``axes`` are SQL of both engines."""
    def run(spark, d):
        g = load(spark, d, "lineitem").groupBy(*[F.expr(x).alias(n) for n, x in axes.items()]).agg(F.count("*").alias("n_lines"))
        return g.select(*axes, "n_lines", *[x.alias(n) for n, x in column().items()])

    inner = ", ".join(f"{x} AS {n}" for n, x in axes.items())
    text = "SELECT " + ", ".join([*axes, "n_lines", *(f"{x} AS {n}" for n, x in sql.items())]) + f" FROM (SELECT {inner}, count(*) AS n_lines FROM lineitem GROUP BY ALL)"
    query(name, text)(run)


c = F.col
_formula("pair_cost_grid", {"p": [35, 50, 100], "w1": [10, 30, 100], "w2": [10, 30], "g": [1, 2]}, lambda: {"value": costs.pair_cost(c("p"), c("w1"), c("w2"), c("g"))}, {"value": "p + w1 + w2 + g"})
_formula("pairwise_total_grid", {"r1": [500, 5000, 10000], "r2": [5000], "w1": [10, 30, 100], "g": [1, 2]}, lambda: {"value": costs.pairwise_cost(c("r1"), c("r2"), 50, c("w1"), 30, c("g"))}, {"value": "(50 + w1 + 30 + g) * r1 * r2"})
_B = {"b1": "l_quantity", "b2": "CAST(l_linenumber AS DOUBLE)", "sigma": "l_discount"}
_table_formula("call_tokens_grid", _B, lambda: {"value": _r(costs.call_tokens(c("b1"), c("b2"), 50, 30, 30, 2, c("sigma")))}, {"value": "round(50 + b1 * 30 + b2 * 30 + b1 * b2 * sigma * 2, 6)"})
_table_formula("call_cost_grid", _B, lambda: {"value": _r(costs.call_cost(c("b1"), c("b2"), 50, 30, 30, 2, c("sigma"), 2))}, {"value": "round(50 + b1 * 30 + b2 * 30 + b1 * b2 * sigma * 2 * 2, 6)"})
_table_formula("call_count_grid", {"b1": "l_quantity", "b2": "CAST(l_linenumber AS DOUBLE)"}, lambda: {"plain": _r(costs.call_count(F.lit(50.0), F.lit(10.0), c("b1"), c("b2"))), "whole": costs.call_count(F.lit(50.0), F.lit(10.0), c("b1"), c("b2"), "ceil").cast("long")}, {"plain": "round((50.0::DOUBLE / b1) * (10.0::DOUBLE / b2), 6)", "whole": "(ceil(50 / b1) * ceil(10 / b2))::BIGINT"})
_table_formula("block_total_grid", _B, lambda: {"value": _r(costs.block_cost(F.lit(5000.0), F.lit(5000.0), c("b1"), c("b2"), 50, 30, 30, 2, c("sigma"), 2), 4)}, {"value": "round((5000 / b1) * (5000 / b2) * (50 + b1 * 30 + b2 * 30 + b1 * b2 * sigma * 2 * 2), 4)"})
_table_formula("feasible_grid", _B, lambda: {"feasible": costs.fits(c("b1"), c("b2"), 30, 30, 2, c("sigma"), 1500)}, {"feasible": "b1 * 30 + b2 * 30 + b1 * b2 * sigma * 2 <= 1500"})
_RIGHT = "((100 - b1 * 10) / (2 + b1 * 1 * sigma))"
_formula("right_size_grid", {"b1": [1, 2, 3, 5, 9], "sigma": SIGMAS}, lambda: {"b2": _r(costs.right_size_for(c("b1"), 10, 2, 1, c("sigma"), 100))}, {"b2": f"round({_RIGHT}, 6)"})
_CURVE = {"b1": [1, 1.5, 2, 2.5, 3, 4, 5, 7, 9], "sigma": [0.01, 0.25, 1.0]}
_table_formula("cost_curve", {"b1": "l_quantity / 6", "sigma": "l_discount"}, lambda: {"cost": _r(costs.cost_on_curve(c("b1"), 50.0, 10.0, 1, 10, 2, 1, c("sigma"), 1, 100), 4)}, {"cost": f"round((50 / b1) * (10 / {_RIGHT}) * (1 + b1 * 10 + {_RIGHT} * 2 + b1 * {_RIGHT} * sigma), 4)"})
_formula("slope_curve", _CURVE, lambda: {"slope": _r(costs.slope_on_curve(c("b1"), 50.0, 10.0, 1, 10, 2, 1, c("sigma"), 100), 4)}, {"slope": "round(50.0 * 10.0 * 101 * (b1 * b1 * 10 * sigma + 2 * b1 * 20 - 200) / ((100 - b1 * 10) * (100 - b1 * 10) * b1 * b1), 4)"})
_LEFT = "(200 / (sqrt(20 * 20 + 20 * sigma * 100) + 20))"
_OPTIMUM_RIGHT = f"((100 - {_LEFT} * 10) / (2 + {_LEFT} * sigma))"


def _best(sigma):
    left = costs.left_size(10, 2, 1, sigma, 100)
    return left, costs.right_size_for(left, 10, 2, 1, sigma, 100)


_formula("optimum_closed_form", {"sigma": [0.0, *SIGMAS]}, lambda: {"b1": _r(_best(c("sigma"))[0]), "b2": _r(_best(c("sigma"))[1]), "cost": _r(costs.cost_when_planned_for(c("sigma"), c("sigma"), 50.0, 10.0, 1, 10, 2, 1, 1, 100), 4)}, {"b1": f"round({_LEFT}, 6)", "b2": f"round({_OPTIMUM_RIGHT}, 6)", "cost": f"round((50 / {_LEFT}) * (10 / {_OPTIMUM_RIGHT}) * (1 + {_LEFT} * 10 + {_OPTIMUM_RIGHT} * 2 + {_LEFT} * {_OPTIMUM_RIGHT} * sigma), 4)"})
_formula("selectivity_batch_sizes", {"sigma": [i / 50 for i in range(51)]}, lambda: {"b1": _r(_best(c("sigma"))[0]), "b2": _r(_best(c("sigma"))[1])}, {"b1": f"round({_LEFT}, 6)", "b2": f"round({_OPTIMUM_RIGHT}, 6)"})
_formula("selectivity_token_split", {"sigma": [i / 50 for i in range(51)]}, lambda: dict(zip(("input_left", "input_right", "output"), map(_r, costs.token_split(10, 2, 1, c("sigma"), 100)))), {"input_left": f"round({_LEFT} * 10, 6)", "input_right": f"round({_OPTIMUM_RIGHT} * 2, 6)", "output": f"round({_LEFT} * {_OPTIMUM_RIGHT} * sigma * 1, 6)"})
_E_LEFT = "(8142 * 30 / (sqrt(900.0 * 900 + 900 * 2 * {e} * 8142) + 900))"
_E_COST = "((5000 / {l}) * (5000 / ((8142 - {l} * 30) / (30 + {l} * 2 * {e}))) * (50 + {l} * 30 + ((8142 - {l} * 30) / (30 + {l} * 2 * {e})) * 30 + {l} * ((8142 - {l} * 30) / (30 + {l} * 2 * {e})) * sigma * 2 * 2))"
_planned = lambda e: _E_COST.format(l=_E_LEFT.format(e=e), e=e)
_formula("regret_grid", {"e": [0.0004, 0.001, 0.004, 0.01, 0.1, 0.4, 1.0], "sigma": [0.0001, 0.0003, 0.001, 0.005, 0.05, 0.3, 1.0]}, lambda: {"regret": _r(costs.regret(c("e"), c("sigma"), 5000.0, 5000.0, 50, 30, 30, 2, 2, 8142)), "bound": costs.regret_bound(F.lit(4.0), 2.0)}, {"regret": f"round({_planned('e')} / {_planned('sigma')}, 6)", "bound": "8.0::DOUBLE"}, ("e >= sigma and sigma >= e / 4", "e >= sigma AND sigma >= e / 4"))
_formula("rounds_grid", {"e": [0.00001, 0.0001, 0.001, 0.01], "sigma": [0.0001, 0.001, 0.01, 0.5, 1.0], "growth": [1.5, 2, 4, 8]}, lambda: {"rounds": costs.expected_rounds(c("e"), c("sigma"), c("growth"))}, {"rounds": "greatest(0, ceil(round(ln(sigma / e) / ln(growth), 9)))::BIGINT"})


@query("cost_surface", "WITH n AS (SELECT DISTINCT l_quantity::BIGINT AS a FROM lineitem WHERE l_quantity IS NOT NULL), g AS (SELECT a AS b_left, b AS b_right, round((50.0::DOUBLE / a) * (10.0::DOUBLE / b) * (1 + a * 10 + b * 2 + a * b), 6) AS cost, a * 10 + b * 2 + a * b <= 100 AS feasible FROM n x(a), n y(b)) SELECT *, feasible AND cost = (SELECT min(cost) FROM g WHERE feasible) AS is_best FROM g")
def cost_surface(spark, d):
    """All pairs of sizes that occur as quantities of lineitem."""
    sizes = load(spark, d, "lineitem").where("l_quantity is not null").select(F.col("l_quantity").cast("long").alias("b_left")).distinct()
    g = sizes.crossJoin(sizes.select(c("b_left").alias("b_right")))
    cost = costs.block_cost(F.lit(50.0), F.lit(10.0), c("b_left"), c("b_right"), 1, 10, 2, 1, 1, 1)
    g = g.select("b_left", "b_right", _r(cost).alias("cost"), costs.fits(c("b_left"), c("b_right"), 10, 2, 1, 1, 100).alias("feasible"))
    best = g.where("feasible").agg(F.min("cost").alias("least"))
    return g.crossJoin(F.broadcast(best)).select("b_left", "b_right", "cost", "feasible", (c("feasible") & (c("cost") == c("least"))).alias("is_best"))


_SMALL = (TableProfile(50, 10.0, 10), TableProfile(10, 2.0, 2))
_RAGGED = "ceil(50 / a) * ceil(10 / b) * 1 + ceil(10 / b) * 50 * 10 + ceil(50 / a) * 10 * 2 + 500 * sigma"


@query("optimum_integer", f"SELECT sigma, round(min({_RAGGED}), 6) AS cost FROM (SELECT unnest({_LIST(SIGMAS)}) AS sigma), (SELECT unnest(range(1, 51))::DOUBLE AS a), (SELECT unnest(range(1, 11))::DOUBLE AS b) WHERE a * 10 + b * 2 + a * b * sigma <= 100 GROUP BY sigma")
def optimum_integer(spark, d):
    """The planner's sizes cost as little as the best of all sizes."""
    return spark.createDataFrame([(s, round(optimize.optimal_batches(*_SMALL, s, 100, 1, 1, 1.0).expected_cost, 6)) for s in SIGMAS], "sigma double, cost double")


@query("optimum_by_search", "SELECT arg_min(a, (cost, -a, -b))::BIGINT AS b_left, arg_min(b, (cost, -a, -b))::BIGINT AS b_right, min(cost) AS cost FROM (SELECT a, b, round(ceil(50.0 / a) * ceil(10.0 / b) * (1 + a * 10 + b * 2 + a * b)::DOUBLE, 6) AS cost FROM range(1, 51) x(a), range(1, 11) y(b) WHERE a * 10 + b * 2 + a * b <= 100)")
def optimum_by_search(spark, d):
    return optimize.best_batches_by_search(spark, 50, 10, 1, 10, 2, 1, 1, 1, 100)


# ---- simulated experiments ----

SWEEP_ROWS = [500, 1000, 2000, 3000, 5000, 7500, 10000]
SWEEP_WIDTH = [10, 20, 30, 50, 75, 100]
SWEEP_SIGMA = [0.0001, 0.0005, 0.001, 0.005, 0.01, 0.1, 0.5, 1.0]


def _sweep_sql(name: str, xs) -> str:
    """Totals of the same calls, in closed form; the adaptive join's voids are found round by round."""
    col = {"rows_left": "5000", "width_left": "30", "selectivity": "0.001::DOUBLE"} | {name: "x"}
    return f"""
        WITH s AS (SELECT x, {col['rows_left']}::DOUBLE AS r1, 5000::DOUBLE AS r2, {col['width_left']} AS w1, 30 AS w2, 2 AS w3, {col['selectivity']} AS sg FROM (SELECT unnest({_LIST(xs)}) AS x)),
        e AS (SELECT *, 'conservative' AS method, 0 AS k, 1.0::DOUBLE AS e FROM s UNION ALL SELECT *, 'informed', 0, sg FROM s
              UNION ALL SELECT s.*, 'adaptive', k, least(1.0, sg * 0.01 * pow(4, k)) FROM s, range(0, 6) t(k)),
        a AS (SELECT *, w2 * 8142 / (sqrt((w1 * w2) * (w1 * w2)::DOUBLE + w1 * w2 * w3 * e * 8142) + w1 * w2) AS l FROM e),
        c AS (SELECT *, greatest(1, least(r1, floor(l + 1e-9))) AS na FROM a),
        b AS (SELECT *, greatest(1, least(r2, floor((8142 - na * w1) / (w2 + na * w3 * e) + 1e-9))) AS nb FROM c),
        o AS (SELECT *, 8142 - na * w1 - nb * w2 AS room, na * nb * sg * w3 > 8142 - na * w1 - nb * w2 + 1e-9 AND e < 1 AND method = 'adaptive' AS bad FROM b),
        f AS (SELECT *, min(CASE WHEN bad THEN 99 ELSE k END) OVER (PARTITION BY x, method) AS last FROM o),
        t AS (SELECT x, method, CASE WHEN k < last THEN 1 ELSE ceil(r1 / na) * ceil(r2 / nb) END AS calls,
                     CASE WHEN k < last THEN 50 + na * w1 + nb * w2 ELSE ceil(r1 / na) * ceil(r2 / nb) * 50 + ceil(r2 / nb) * r1 * w1 + ceil(r1 / na) * r2 * w2 END AS rd,
                     CASE WHEN k < last THEN least(room, na * nb * sg * w3) ELSE r1 * r2 * sg * w3 END AS wr FROM f WHERE k <= last
              UNION ALL SELECT x, 'pairwise', r1 * r2, r1 * r2 * (50 + w1 + w2), r1 * r2 FROM s)
        SELECT x, method, sum(calls)::BIGINT AS calls, sum(rd)::BIGINT AS tokens_read, round(sum(wr), 3) AS tokens_written, round((sum(rd) * 0.03 + sum(wr) * 0.06) / 1000, 2) AS fee
        FROM t GROUP BY x, method"""


for _name, _field, _xs in (("sweep_rows", "rows_left", SWEEP_ROWS), ("sweep_width", "width_left", SWEEP_WIDTH), ("sweep_selectivity", "selectivity", SWEEP_SIGMA)):
    query(_name, _sweep_sql(_field, _xs))(lambda spark, d, f=_field, xs=_xs: simulate.simulate(spark, simulate.sweep(simulate.Setting(), f, xs)))


@query("price_example", "SELECT 'pairwise' AS method, 600000.0::DOUBLE AS fee")
def price_example(spark, d):
    """10,000 rows of 100 tokens on either side, reading only, 3 cents per 1,000."""
    return spark.createDataFrame([("pairwise", costs.fee_cents(costs.pairwise_cost(10_000, 10_000, 0, 100, 100, 0), 0) / 100)], "method string, fee double")


@query("price_statement", f"WITH f AS (SELECT method, fee FROM ({_sweep_sql('rows_left', [10000])})) SELECT 'pairwise' AS method, (SELECT fee FROM f WHERE method = 'pairwise') > 100000 AS holds UNION ALL SELECT 'adaptive', (SELECT fee FROM f WHERE method = 'adaptive') < least(1000, 1.002 * (SELECT fee FROM f WHERE method = 'informed')) UNION ALL SELECT 'conservative', (SELECT fee FROM f WHERE method = 'conservative') / (SELECT fee FROM f WHERE method = 'informed') BETWEEN 2 AND 3.5")
def price_statement(spark, d):
    """10,000 x 5,000: pairwise above $100,000, adaptive below $1,000 and within 0.2 % of informed, conservative 2-3.5 times as dear."""
    s = simulate.Setting(rows_left=10_000)
    fee = {r["method"]: r["fee"] for r in simulate.simulate(spark, [(0.0, s)]).collect()}
    rows = [("pairwise", fee["pairwise"] > 100_000), ("adaptive", fee["adaptive"] < min(1000, 1.002 * fee["informed"])), ("conservative", 2 < fee["conservative"] / fee["informed"] < 3.5)]
    return spark.createDataFrame(rows, "method string, holds boolean")


# ---- semantic joins on the workloads ----

W1_SQL = """m AS (SELECT o_orderkey, o_custkey, strftime(o_orderdate, '%Y-%m') AS mon FROM orders),
    chosen AS (SELECT o_custkey FROM m GROUP BY 1 HAVING count(DISTINCT mon) >= 2 ORDER BY 1 LIMIT 10),
    ranked AS (SELECT o_custkey, mon, row_number() OVER (PARTITION BY o_custkey ORDER BY mon) AS k FROM (SELECT DISTINCT o_custkey, mon FROM m JOIN chosen USING (o_custkey))),
    claims AS (SELECT o_custkey, mon AS said FROM ranked WHERE k = CASE WHEN o_custkey % 2 = 0 THEN 2 ELSE 1 END),
    lhs AS (SELECT o_orderkey AS id, 'Order taken from Customer#' || lpad(o_custkey::VARCHAR, 9, '0') || ' in ' || mon || '.' AS text FROM m JOIN chosen USING (o_custkey)),
    rhs AS (SELECT o_custkey AS id, 'Customer#' || lpad(o_custkey::VARCHAR, 9, '0') || ': my first order was in ' || said || '.' AS text FROM claims),
    truth AS (SELECT o_orderkey AS left_id, o_custkey AS right_id FROM m JOIN claims USING (o_custkey) WHERE mon < said)"""
W2_SQL = f"""x AS (SELECT doc_id, quality, list_aggregate(regexp_extract_all(text, '{P}')[1:100], 'string_agg', ' ') AS text, row_number() OVER (PARTITION BY quality ORDER BY doc_id) AS k FROM documents JOIN labels USING (doc_id)),
    n AS (SELECT least(25, min(c) // 2) AS n FROM (SELECT count(*) AS c FROM x GROUP BY quality)),
    lhs AS (SELECT doc_id AS id, text, quality FROM x, n WHERE k <= n.n), rhs AS (SELECT doc_id AS id, text, quality FROM x, n WHERE k > n.n AND k <= 2 * n.n),
    truth AS (SELECT l.id AS left_id, r.id AS right_id FROM lhs l JOIN rhs r USING (quality))"""
W3_SQL = """w AS (SELECT DISTINCT split_part(p_name, ' ', 1) AS a, split_part(p_name, ' ', 2) AS n FROM part),
    a AS (SELECT a, row_number() OVER (ORDER BY a) - 1 AS i FROM (SELECT DISTINCT a FROM w ORDER BY a LIMIT 4)),
    n AS (SELECT n, row_number() OVER (ORDER BY n) - 1 AS j FROM (SELECT DISTINCT n FROM w ORDER BY n LIMIT 4)),
    lhs AS (SELECT i * 4 + j AS id, 'For sale: a ' || n || ', ' || a || '.' AS text FROM a, n), rhs AS (SELECT i * 4 + j AS id, 'Wanted: a ' || n || ' in ' || a || '.' AS text FROM a, n),
    truth AS (SELECT id AS left_id, id AS right_id FROM lhs)"""
W3B_SQL = """p AS (SELECT p_partkey, split_part(p_name, ' ', 1) AS a, p_type AS t FROM part),
    kinds AS (SELECT a, t, row_number() OVER (ORDER BY a, t) - 1 AS id FROM (SELECT DISTINCT a, t FROM p)),
    truth AS (SELECT p_partkey AS left_id, id AS right_id FROM p JOIN kinds USING (a, t))"""
REPLIES_SQL = "truth AS (SELECT u.conv_id * 1000 + u.turn AS left_id, a.conv_id * 1000 + a.turn AS right_id FROM conversations u JOIN conversations a ON a.conv_id = u.conv_id AND a.turn = u.turn + 1 WHERE u.role = 'user' AND a.role = 'assistant')"
_WITH = {"contradiction": W1_SQL, "sentiment": W2_SQL, "offers": W3_SQL}
TRUTH = " SELECT left_id::BIGINT AS left_id, right_id::BIGINT AS right_id FROM truth"


def _model(w: workloads.Workload, context: int = 2000, reliable: int | None = None) -> TruthModel:
    return TruthModel(w.predicate, ModelProfile(context_tokens=context, reliable_tokens=reliable))


def _make(name: str, spark, d) -> workloads.Workload:
    return getattr(workloads, name)(spark, d)


def _joined(spark: SparkSession, d: str, name: str, method: str) -> JoinRun:
    w = _make(name, spark, d)
    m = _model(w)
    if method == "pairwise":
        return joins.pairwise_join(w.left, w.right, w.predicate, m)
    if method == "block":
        return joins.block_join_planned(w.left, w.right, w.predicate, m)
    return joins.adaptive_join(w.left, w.right, w.predicate, m, 0.0001)


for _w, _sql in _WITH.items():
    for _m in ("pairwise", "block", "adaptive"):
        query(f"{_w}_{_m}", f"WITH {_sql}{TRUTH}")(lambda spark, d, w=_w, m=_m: _joined(spark, d, w, m).pairs)


def _unstratified(label: str) -> str:
    return f"WITH f AS (SELECT doc_id, {label} AS label, row_number() OVER (ORDER BY doc_id) AS k FROM (SELECT * FROM labels JOIN documents USING (doc_id) ORDER BY doc_id LIMIT 100)), truth AS (SELECT l.doc_id AS left_id, r.doc_id AS right_id FROM f l JOIN f r USING (label) WHERE l.k <= 50 AND r.k > 50){TRUTH}"


#: The published size of this experiment is 50 x 50; ``toxic_whole`` has all labelled documents.
for _n, _l in (("toxic_adaptive", "toxic"), ("quality_adaptive", "quality"), ("both_labels_adaptive", "quality * 2 + toxic")):
    query(_n, _unstratified(_l))(lambda spark, d, label=_l: (lambda w: joins.adaptive_join(w.left, w.right, w.predicate, _model(w), 0.0001).pairs)(workloads.toxic(spark, d, label)))


@query("offers_large_adaptive", f"WITH {W3B_SQL}{TRUTH}")
def offers_large_adaptive(spark, d):
    w = workloads.offers_large(spark, d)
    return joins.adaptive_join(w.left, w.right, w.predicate, _model(w), 0.001, restart="failed").pairs


_QUOTES = "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)"


def _quotes(spark, d, adaptive: bool):
    w = workloads.quotes(spark, d)
    m = _model(w, 8192, 5000)  # chunks vary in width, so plans leave room
    run = joins.adaptive_join(w.left, w.right, w.predicate, m, 0.0001, restart="failed") if adaptive else joins.block_join_planned(w.left, w.right, w.predicate, m, 0.05)
    return workloads.documents_of(run.pairs, w.stride)


query("quotes_block", _QUOTES)(lambda spark, d: _quotes(spark, d, False))
query("quotes_adaptive", _QUOTES)(lambda spark, d: _quotes(spark, d, True))


def _replies(spark, d, method: str) -> tuple[workloads.Workload, JoinRun]:
    """An answer lies in the same conversation: that equal key keeps the calls in proportion to the turns."""
    w = workloads.replies(spark, d)
    m = _model(w, 8192, 5000)
    if method == "block":
        return w, joins.block_join_planned(w.left, w.right, w.predicate, m, 0.02, on="conv_id")
    return w, joins.adaptive_join(w.left, w.right, w.predicate, m, 0.0001, restart="failed", on="conv_id")


query("replies_block", f"WITH {REPLIES_SQL}{TRUTH}")(lambda spark, d: _replies(spark, d, "block")[1].pairs)
query("replies_adaptive", f"WITH {REPLIES_SQL}{TRUTH}")(lambda spark, d: _replies(spark, d, "adaptive")[1].pairs)


@query("replies_topk", f"WITH {REPLIES_SQL}{TRUTH} ORDER BY left_id, right_id LIMIT 20")
def replies_topk(spark, d):
    return variants.first_pairs(_replies(spark, d, "block")[1].pairs, 20)


@query("language_adaptive", "SELECT page_id, doc_id FROM (SELECT page_id, regexp_extract(url, '://[^/]+/([a-z]+)/', 1) AS lang FROM pages) JOIN documents USING (lang)")
def language_adaptive(spark, d):
    """Being in the same language is an equivalence: every row is asked about once with a page of each language."""
    w = workloads.language(spark, d)
    pages, parts = variants.classes_of(w.left, w.right, w.predicate, _model(w, 8192, 6000), 0.1)
    docs = parts.select(workloads.document_of(c("row_id"), w.stride).alias("doc_id"), "class_id").distinct()
    return variants.within_classes(pages.select(c("row_id").alias("page_id"), "class_id"), docs, "class_id").select("page_id", "doc_id")


_COSINE = """v AS (SELECT vec_id, embedding::DOUBLE[] AS e, label FROM embeddings),
    s AS (SELECT l.vec_id AS left_id, r.vec_id AS right_id, round(list_cosine_similarity(l.e, r.e), 12) AS sim, l.label = r.label AS hit FROM v l, v r WHERE l.vec_id % 2 = 0 AND r.vec_id % 2 = 1),
    k AS (SELECT *, row_number() OVER (PARTITION BY left_id ORDER BY sim DESC, right_id) AS rank FROM s)"""


@query("clusters_embedding", f"WITH {_COSINE} SELECT left_id, right_id FROM k WHERE rank = 1")
def clusters_embedding(spark, d):
    w = workloads.clusters(spark, d)
    return embedding.embedding_join(w.left, w.right).pairs


@query("clusters_quality", f"WITH {_COSINE}, q AS (SELECT (SELECT count(*) FROM s WHERE hit) AS t, (SELECT count(*) FROM k WHERE rank = 1) AS n, (SELECT count(*) FROM k WHERE rank = 1 AND hit) AS h) SELECT round(h / t, 6) AS recall, round(h / n, 6) AS precision, round(2 * (h / t) * (h / n) / (h / t + h / n), 6) AS f1 FROM q")
def clusters_quality(spark, d):
    w = workloads.clusters(spark, d)
    q = quality.quality(embedding.embedding_join(w.left, w.right).pairs, w.truth)
    return q.select(*[_r(c(x)).alias(x) for x in ("recall", "precision", "f1")])


@query("embedding_prefilter", f"WITH {_COSINE} SELECT left_id, right_id FROM k WHERE rank <= 5")
def embedding_prefilter(spark, d):
    w = workloads.clusters(spark, d)
    return embedding.embedding_prefilter(w.left, w.right, top_k=5)


@query("offers_embedding", f"WITH {W3_SQL}{TRUTH}")
def offers_embedding(spark, d):
    w = workloads.offers(spark, d)
    return embedding.embedding_join(w.left, w.right, embedding.HashingEmbedder()).pairs


@query("offers_prefiltered_pairwise", f"WITH {W3_SQL}{TRUTH}")
def offers_prefiltered_pairwise(spark, d):
    w = workloads.offers(spark, d)
    some = embedding.embedding_prefilter(w.left, w.right, embedding.HashingEmbedder(), 3)
    return joins.parallel_pairwise_engine(w.left, w.right, w.predicate, _model(w), 8, some).pairs


@query("offers_parallel_engine", f"WITH {W3_SQL}{TRUTH}")
def offers_parallel_engine(spark, d):
    w = workloads.offers(spark, d)
    return joins.parallel_pairwise_engine(w.left, w.right, w.predicate, _model(w), 8).pairs


# ---- noise and quality ----

MISS, ALARM, SEED = 0.2, 0.02, 7
_U = f"(('0x' || left(md5(l.id::VARCHAR || ':' || r.id::VARCHAR || ':{SEED}'), 8))::BIGINT / 4294967296.0)"
_NOISY = f"noisy AS (SELECT l.id::BIGINT AS left_id, r.id::BIGINT AS right_id, t.left_id IS NOT NULL AS hit FROM lhs l CROSS JOIN rhs r LEFT JOIN truth t ON t.left_id = l.id AND t.right_id = r.id WHERE CASE WHEN t.left_id IS NOT NULL THEN {_U} >= {MISS} ELSE {_U} < {ALARM} END)"


def _noisy(spark, d, name: str, method: str) -> JoinRun:
    w = _make(name, spark, d)
    m = NoisyModel(w.predicate, ModelProfile(), miss=MISS, false_alarm=ALARM, seed=SEED)
    if method == "pairwise":
        return joins.pairwise_join(w.left, w.right, w.predicate, m)
    if method == "adaptive":
        return joins.adaptive_join(w.left, w.right, w.predicate, m, 0.001)
    return joins.block_join_planned(w.left, w.right, w.predicate, m)


for _w in ("offers", "sentiment"):
    query(f"{_w}_noisy", f"WITH {_WITH[_w]}, {_NOISY} SELECT left_id, right_id FROM noisy")(lambda spark, d, w=_w: _noisy(spark, d, w, "block").pairs)

_METHODS = ("pairwise", "block", "adaptive")
_QUALITY = lambda w: f"(WITH {_WITH[w]}, {_NOISY}, q AS (SELECT (SELECT count(*) FROM truth) AS t, (SELECT count(*) FROM noisy) AS n, (SELECT count(*) FROM noisy WHERE hit) AS h) SELECT '{w}' AS workload, unnest({list(_METHODS)}) AS method, round(h / t, 6) AS recall, round(h / n, 6) AS precision, round(2 * (h / t) * (h / n) / (h / t + h / n), 6) AS f1 FROM q)"


@query("quality_by_operator", " UNION ALL ".join(map(_QUALITY, _WITH)))
def quality_by_operator(spark, d):
    out = []
    for w in _WITH:
        truth = _make(w, spark, d).truth
        for m in _METHODS:
            q = quality.quality(_noisy(spark, d, w, m).pairs, truth)
            out.append(q.select(F.lit(w).alias("workload"), F.lit(m).alias("method"), *[_r(c(x)).alias(x) for x in ("recall", "precision", "f1")]))
    return joins._union(out)


# ---- usage and fees ----

_SIZE = 10  # rows of a batch on either side, in order of ids, so that SQL can recompute the tokens
_SHAPES = {name: (SemanticPredicate(text), PromptStyle()) for name, text in (("contradiction", "the two notes contradict each other on when the customer first ordered"), ("sentiment", "both texts are well written, or both are poor"), ("offers", "the offer meets the request"))}


def _usage_sql(w: str) -> str:
    pred, style = _SHAPES[w]
    pair, block, over = style.instruction_tokens(pred.text, "pair"), style.instruction_tokens(pred.text), style.row_overhead
    return f"""(WITH {_WITH[w]}, z AS (SELECT (SELECT count(*) FROM lhs) AS n, (SELECT count(*) FROM rhs) AS m, (SELECT sum({_words('text')}) FROM lhs) AS wl, (SELECT sum({_words('text')}) FROM rhs) AS wr, (SELECT count(*) FROM truth) AS t),
        y AS (SELECT *, ceil(n / {_SIZE}.0) AS nl, ceil(m / {_SIZE}.0) AS nr FROM z)
        SELECT 'pairwise' AS method, (n * m)::BIGINT AS calls, (n * m * {pair} + m * wl + n * wr)::BIGINT AS tokens_read, (n * m)::BIGINT AS tokens_written FROM y
        UNION ALL SELECT 'block', (nl * nr)::BIGINT, (nl * nr * {block} + nr * (wl + n * {over}) + nl * (wr + m * {over}))::BIGINT, (4 * t + nl * nr)::BIGINT FROM y
        UNION ALL SELECT 'embedding', 1::BIGINT, (wl + wr)::BIGINT, 0::BIGINT FROM y)"""


def _usage(spark, d, w: str) -> DataFrame:
    x = _make(w, spark, d)
    m = _model(x, 8192)
    runs = [joins.pairwise_join(x.left, x.right, x.predicate, m), joins.block_join(x.left, x.right, x.predicate, m, _SIZE, _SIZE, order="key"), embedding.embedding_join(x.left, x.right, embedding.HashingEmbedder(64))]
    return joins._union([r.usage().select(F.lit(r.method).alias("method"), "calls", "tokens_read", "tokens_written") for r in runs])


for _w in _WITH:
    query(f"{_w}_usage", _usage_sql(_w))(lambda spark, d, w=_w: _usage(spark, d, w))

_ALL_USAGE = " UNION ALL ".join(f"SELECT '{w}' AS workload, * FROM {_usage_sql(w)}" for w in _WITH)


def _all_usage(spark, d) -> DataFrame:
    return Scratch(spark, "usage").table(joins._union([_usage(spark, d, w).withColumn("workload", F.lit(w)) for w in _WITH]), "usage")


_FEE_SQL = "(CASE WHEN method = 'embedding' THEN tokens_read * 2 / 1000000.0 ELSE (tokens_read * 3 + tokens_written * 6) / 1000.0 END)"


def _fee() -> Column:
    dec = lambda x, price: c(x).cast("decimal(18,0)") * F.lit(price).cast("decimal(12,6)")
    chat = dec("tokens_read", 0.003) + dec("tokens_written", 0.006)
    return F.when(c("method") == "embedding", dec("tokens_read", embedding.EmbedderProfile().price / 1000)).otherwise(chat)


@query("fees_by_operator", f"SELECT workload, method, round({_FEE_SQL}::DOUBLE, 4) AS fee FROM ({_ALL_USAGE})")
def fees_by_operator(spark, d):
    return _all_usage(spark, d).select("workload", "method", _r(_fee().cast("double"), 4).alias("fee"))


_SUMS = "sum(calls)::BIGINT AS calls, sum(tokens_read)::BIGINT AS tokens_read, sum(tokens_written)::BIGINT AS tokens_written"
_sums = lambda: [F.sum(x).alias(x) for x in ("calls", "tokens_read", "tokens_written")]
query("usage_rollup", f"SELECT workload, method, {_SUMS} FROM ({_ALL_USAGE}) GROUP BY ROLLUP (workload, method)")(lambda spark, d: _all_usage(spark, d).rollup("workload", "method").agg(*_sums()))
query("usage_cube", f"SELECT workload, method, {_SUMS} FROM ({_ALL_USAGE}) GROUP BY CUBE (workload, method)")(lambda spark, d: _all_usage(spark, d).cube("workload", "method").agg(*_sums()))
query("usage_pivot", f"SELECT workload, sum(tokens_read) FILTER (WHERE method = 'pairwise')::BIGINT AS pairwise, sum(tokens_read) FILTER (WHERE method = 'block')::BIGINT AS block, sum(tokens_read) FILTER (WHERE method = 'embedding')::BIGINT AS embedding FROM ({_ALL_USAGE}) GROUP BY workload")(lambda spark, d: _all_usage(spark, d).groupBy("workload").pivot("method", ["pairwise", "block", "embedding"]).agg(F.sum("tokens_read")))


@query("benchmark_statistics", " UNION ALL ".join(f"(WITH {_WITH[w]} SELECT '{w}' AS workload, (SELECT count(*) FROM lhs) AS rows_left, (SELECT count(*) FROM rhs) AS rows_right, (SELECT round(avg({_words('text')}), 6) FROM lhs) AS width_left, (SELECT round(avg({_words('text')}), 6) FROM rhs) AS width_right, round((SELECT count(*) FROM truth) / ((SELECT count(*) FROM lhs) * (SELECT count(*) FROM rhs)), 6) AS selectivity)" for w in _WITH))
def benchmark_statistics(spark, d):
    out = []
    for w in _WITH:
        x = _make(w, spark, d)
        s = quality.benchmark_statistics(x.left, x.right, x.truth)
        out.append(s.select(F.lit(w).alias("workload"), "rows_left", "rows_right", _r(c("width_left")).alias("width_left"), _r(c("width_right")).alias("width_right"), _r(c("selectivity")).alias("selectivity")))
    return joins._union(out)


@query("overflow_rounds")
def overflow_rounds(spark, d):
    """An adaptive join that starts far too low on a workload where half of all pairs match."""
    w = workloads.sentiment(spark, d)
    run = joins.adaptive_join(w.left, w.right, w.predicate, _model(w, 1200), 0.0001)
    return spark.createDataFrame([(r.number, r.estimate, r.batch_left, r.batch_right, r.overflow) for r in run.rounds], "round int, estimate double, b_left int, b_right int, overflow boolean")


# ---- variants ----


def _offers_half(spark, d):
    """Requests for the first adjective only, so that other offers have no partner."""
    w = workloads.offers(spark, d)
    right = w.right.where("row_id < 4")
    return w, joins.block_join_planned(w.left, right, w.predicate, _model(w))


query("offers_semi", f"WITH {W3_SQL} SELECT id::BIGINT AS row_id FROM lhs WHERE id < 4")(lambda spark, d: (lambda x: variants.semi(x[0].left, x[1]).select("row_id"))(_offers_half(spark, d)))
query("offers_anti", f"WITH {W3_SQL} SELECT id::BIGINT AS row_id FROM lhs WHERE id >= 4")(lambda spark, d: (lambda x: variants.anti(x[0].left, x[1]).select("row_id"))(_offers_half(spark, d)))
query("offers_outer", f"WITH {W3_SQL} SELECT id::BIGINT AS left_id, CASE WHEN id < 4 THEN id END::BIGINT AS right_id FROM lhs")(lambda spark, d: (lambda x: variants.left_outer(x[0].left, x[1]))(_offers_half(spark, d)))


@query("hybrid_same_customer", f"WITH {W1_SQL.replace(' ORDER BY 1 LIMIT 10', '')}{TRUTH}")
def hybrid_same_customer(spark, d):
    """All customers, not ten: the equal key makes their orders affordable."""
    w = workloads.contradiction(spark, d, customers=None)
    return joins.hybrid_join(w.left, w.right, "o_custkey", w.predicate, _model(w), 20, 5).pairs


def _good(a, b) -> bool:
    return a[1] == "1"


def _chunks_that(spark, d, label: str, text: str) -> DataFrame:
    """(doc_id, n, met): of every labelled document the chunks of its whole text and how many of them meet the condition."""
    docs = load(spark, d, "labels").select("doc_id", label).join(load(spark, d, "documents").select("doc_id", "text"), "doc_id")
    parts = tokens.chunks(docs.withColumn("key", c(label).cast("string")), workloads.CHUNK, 0, "doc_id", keep=("key",))
    parts = Scratch(spark, "chunks").table(parts, "chunks")
    stride = workloads.stride_of(parts, "chunk")
    rows = parts.select((c("doc_id") * stride + c("chunk")).alias("row_id"), "text", "key")
    pred = SemanticPredicate(text, EachPair(_good))
    found = joins.semantic_filter(rows, pred, TruthModel(pred, ModelProfile(context_tokens=8192)), 12).pairs
    met = found.groupBy(workloads.document_of(c("left_id"), stride).alias("doc_id")).agg(F.count("*").alias("met"))
    n = rows.groupBy(workloads.document_of(c("row_id"), stride).alias("doc_id")).agg(F.count("*").alias("n"))
    return n.join(met, "doc_id", "left").select("doc_id", "n", F.coalesce("met", F.lit(0)).alias("met"))


@query("semantic_filter_quality", "SELECT doc_id FROM labels JOIN documents USING (doc_id) WHERE quality = 1")
def semantic_filter_quality(spark, d):
    """All labelled documents; one is well written if all of its text is."""
    return _chunks_that(spark, d, "quality", "the text is well written").where("met = n").select("doc_id")


@query("toxic_whole", "WITH f AS (SELECT doc_id, toxic FROM labels JOIN documents USING (doc_id)) SELECT l.doc_id AS left_id, r.doc_id AS right_id FROM f l JOIN f r USING (toxic) WHERE l.doc_id % 2 = 0 AND r.doc_id % 2 = 1")
def toxic_whole(spark, d):
    """All labelled documents, even ids against odd ones: each is asked about once, and what is asked about both follows."""
    f = Scratch(spark, "toxic").table(_chunks_that(spark, d, "toxic", "the text is toxic").select("doc_id", (c("met") > 0).alias("toxic")))
    side = lambda k, name: f.where(c("doc_id") % 2 == k).select(c("doc_id").alias(name), "toxic")
    return variants.within_classes(side(0, "left_id"), side(1, "right_id"), "toxic").select("left_id", "right_id")


@query("dedup_texts", "SELECT count(*) AS n_texts, count(DISTINCT text) AS n_distinct, count(*) - count(DISTINCT text) AS saved_calls FROM documents")
def dedup_texts(spark, d):
    return load(spark, d, "documents").agg(F.count("*").alias("n_texts"), F.countDistinct("text").alias("n_distinct")).withColumn("saved_calls", c("n_texts") - c("n_distinct"))


@query("dedup_join", f"WITH {W3B_SQL}{TRUTH}")
def dedup_join(spark, d):
    """Equal offers are asked about once; their pairs go to all of them."""
    w = workloads.offers_large(spark, d)
    return joins.with_distinct_texts(joins.block_join_planned, w.left, w.right, w.predicate, _model(w), 0.1).pairs


def _two(spark, d):
    w = workloads.offers(spark, d)
    noisy = NoisyModel(w.predicate, ModelProfile(), miss=MISS, false_alarm=ALARM, seed=SEED)
    return joins.pairwise_join(w.left, w.right, w.predicate, _model(w)).pairs, joins.block_join_planned(w.left, w.right, w.predicate, noisy).pairs


query("result_difference", f"WITH {W3_SQL}, {_NOISY}{TRUTH} EXCEPT SELECT left_id, right_id FROM noisy")(lambda spark, d: (lambda x: x[0].exceptAll(x[1]))(_two(spark, d)))
query("result_intersection", f"WITH {W3_SQL}, {_NOISY}{TRUTH} INTERSECT SELECT left_id, right_id FROM noisy")(lambda spark, d: (lambda x: x[0].intersect(x[1]))(_two(spark, d)))


@query("stream_replay_equals_batch", f"WITH {W3B_SQL}{TRUTH}")
def stream_replay_equals_batch(spark, d):
    """Parts arrive as a stream and are joined with the standing requests."""
    from semjoin.streaming import stream_semantic_join

    w = workloads.offers_large(spark, d)
    # As a pattern, the path may be a file or a folder; files of other tables' folders are named part-* as well.
    parts = spark.readStream.schema(load(spark, d, "part").schema).parquet(f"{d}/part.parque[t]")
    arriving = parts.select(c("p_partkey").alias("row_id"), F.concat(F.lit("For sale: something "), F.split_part("p_name", F.lit(" "), F.lit(1)), F.lit(", type "), "p_type", F.lit(".")).alias("text"), F.lit(None).cast("string").alias("key"))
    base = f"{shared_root(spark)}/stream-{uuid.uuid4().hex[:12]}"
    q, _ = stream_semantic_join(arriving, w.right, w.predicate, _model(w), f"{base}/out", f"{base}/state", 0.01)
    q.awaitTermination()
    return spark.read.parquet(f"{base}/out").select("left_id", "right_id")


@query("udtf_block_answers", f"WITH {W3_SQL}{TRUTH}")
def udtf_block_answers(spark, d):
    w = workloads.offers(spark, d)
    variants.register_block_answers(spark, "block_answers", w.predicate, _model(w))
    batching.make_cells(batching.make_batches(w.left, 5), batching.make_batches(w.right, 6), 0).createOrReplaceTempView("semjoin_cells")
    return spark.sql("SELECT left_id, right_id FROM block_answers(TABLE(semjoin_cells))")


@query("udf_pair_match", f"WITH {W3_SQL}{TRUTH}")
def udf_pair_match(spark, d):
    w = workloads.offers(spark, d)
    variants.register_match(spark, "semantic_match", w.predicate, _model(w))
    w.left.createOrReplaceTempView("semjoin_l")
    w.right.createOrReplaceTempView("semjoin_r")
    return spark.sql("SELECT l.row_id AS left_id, r.row_id AS right_id FROM semjoin_l l CROSS JOIN semjoin_r r WHERE semantic_match(l.text, r.text)")


@query("sql_semantic_join", f"WITH {W3_SQL} SELECT count(*) AS n_pairs FROM truth")
def sql_semantic_join(spark, d):
    w = workloads.offers(spark, d)
    w.left.createOrReplaceTempView("semjoin_l")
    w.right.createOrReplaceTempView("semjoin_r")
    variants.semantic_join(spark, "semjoin_l", "semjoin_r", w.predicate, _model(w), "adaptive", "semjoin_found", start_estimate=0.01)
    return spark.sql("SELECT count(*) AS n_pairs FROM semjoin_found")


@query("chunk_documents", f"SELECT doc_id, greatest(1, 1 + ceil(({_words('text')} - 400) / 280.0))::BIGINT AS n_chunks FROM documents")
def chunk_documents(spark, d):
    docs = load(spark, d, "documents").select(c("doc_id").alias("row_id"), "text")
    return tokens.chunks(docs, workloads.CHUNK, workloads.OVERLAP).groupBy(c("row_id").alias("doc_id")).agg(F.count("*").alias("n_chunks"))
