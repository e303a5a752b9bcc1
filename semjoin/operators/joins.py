"""The semantic joins: pairwise, block, and adaptive."""

from __future__ import annotations

import math
import time
import uuid
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semjoin import schemas
from semjoin.functions import parse
from semjoin.functions.tokens import count_column
from semjoin.lm.base import SemanticPredicate
from semjoin.operators.ask import ask, ask_cached, ledger_of
from semjoin.operators.batching import BROADCAST_BYTES, buckets_for, cut_batches, indexed, make_batches, make_cells, pack_batches
from semjoin.plans.optimize import optimal_batches
from semjoin.plans.profile import profile_tables
from semjoin.prompts import PromptStyle
from semjoin.state import Scratch
from semjoin.types import BatchPlan, BudgetTooSmall, FeeLimit, JoinRun, OverflowSignal, Round, TableProfile

WIDTH_MATCH = 4  # tokens of "1,2;"
MANY = 32  # batches a task: so many fall evenly enough where they are formed
PROBES = 7  # cells that are asked in waves of 1, 2 and 4 before the others


def _new_run(method: str) -> str:
    return f"{method}-{uuid.uuid4().hex[:8]}"


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def tasks_for(left: DataFrame, model, parallelism: int | None) -> int:
    """Tasks that calls are dealt to: what is asked for, what the service allows, or the cores."""
    return parallelism or model.profile.max_parallel or left.sparkSession.sparkContext.defaultParallelism


def check_fee(model, tokens_read: float, tokens_written: float, max_fee: float | None) -> None:
    """Refuses what would cost more than ``max_fee`` cents."""
    fee = (tokens_read * model.profile.read_price + tokens_written * model.profile.write_price) / 1000
    if max_fee is not None and fee > max_fee:
        raise FeeLimit(f"{fee:.2f} cents are forecast, {max_fee} allowed")


def _singles(rows: DataFrame) -> DataFrame:
    """Every row as a batch of its own, under its id."""
    item = F.struct(F.lit(1).alias("pos"), "row_id", "text", "key", F.lit(0).alias("tokens"))
    return rows.select(F.col("row_id").alias("batch_id"), F.array(item).alias("items"))


def pairwise_join(left: DataFrame, right: DataFrame, predicate: SemanticPredicate, model, style: PromptStyle | None = None, max_output: int = 1, parallelism: int | None = None, candidates: DataFrame | None = None, method: str = "pairwise", max_fee: float | None = None, profiles: tuple[TableProfile, TableProfile] | None = None, cache=None) -> JoinRun:
    """One prompt per pair; ``candidates`` (left_id, right_id) restricts the pairs, e.g. to a prefilter's."""
    began, style, run_id = time.perf_counter(), style or PromptStyle(), _new_run(method)
    scratch = Scratch(left.sparkSession, run_id)
    model = replace(model, profile=replace(model.profile, max_output=max_output))
    tasks = tasks_for(left, model, parallelism)
    l, r = _singles(left), _singles(right)  # noqa: E741
    if candidates is None:
        profiles = profiles or profile_tables(left, right, style.counter)
        n, m = (p.rows for p in profiles)
        check_fee(model, n * m * (style.instruction_tokens(predicate.text, "pair") + profiles[0].width_mean + profiles[1].width_mean), n * m * max_output, max_fee)
        cells = make_cells(l, r, _bytes_bound(profiles[1]), parallelism=tasks, counts=(n, m))
        tasks = None
    else:
        c = candidates.select("left_id", "right_id").distinct()
        if max_fee is not None:
            w = lambda rows, i: rows.select(F.col("row_id").alias(i), count_column(F.col("text"), style.counter).cast("long").alias(f"w_{i}"))
            n, read = c.join(w(left, "left_id"), "left_id").join(w(right, "right_id"), "right_id").agg(F.count("*"), F.coalesce(F.sum(F.col("w_left_id") + F.col("w_right_id")), F.lit(0))).first()
            check_fee(model, n * style.instruction_tokens(predicate.text, "pair") + read, n * max_output, max_fee)
        side = lambda x, s: x.select(F.col("batch_id").alias(f"{s}_batch"), F.col("items").alias(f"{s}_items"))
        cells = c.join(side(l, "left"), F.col("left_id") == F.col("left_batch")).join(side(r, "right"), F.col("right_id") == F.col("right_batch"))
    asked = ask_cached(cells, model, predicate.text, style, "pair", cache, scratch) if cache else ask(cells, model, predicate.text, style, "pair", tasks)
    answers = scratch.table(asked, "answers")
    found = answers.where(parse.read_verdict(F.col("answer"))).select(F.col("left_batch").alias("left_id"), F.col("right_batch").alias("right_id"))
    ledger = ledger_of(answers, run_id, 0, ~F.col("stopped"), parse.is_malformed(F.col("answer")))
    return JoinRun(run_id, method, found, ledger, seconds=time.perf_counter() - began)


def parallel_pairwise_engine(left: DataFrame, right: DataFrame, predicate: SemanticPredicate, model, parallelism: int = 64, candidates: DataFrame | None = None, max_fee: float | None = None) -> JoinRun:
    """The pair-per-prompt baseline of an existing engine: longer instructions, three written tokens, calls at once."""
    return pairwise_join(left, right, predicate, model, PromptStyle(verbose=True), 3, parallelism, candidates, "parallel_pairwise", max_fee)


def _bytes_bound(p: TableProfile) -> int:
    return p.rows * (p.width_max * 16 + 64)


def _cells(sides, sizes, profiles, tasks: int, only: list[tuple[int, int]] | None = None, skip: list[tuple[int, int]] | None = None) -> DataFrame:
    """Cells of indexed sides: all, those named, or all but those named (both lists are short)."""
    named = lambda k: sorted({x[k] for x in only}) if only is not None else None
    counts = tuple(max(1, -(-p.rows // b)) for p, b in zip(profiles, sizes))
    bound = _bytes_bound(profiles[1])
    dealt = max(tasks, counts[0] // 1000) if only is None and counts[0] >= MANY * tasks and bound <= BROADCAST_BYTES else None
    l, r = (cut_batches(side, size, only=named(k), tasks=None if k else dealt) for k, (side, size) in enumerate(zip(sides, sizes)))  # noqa: E741
    cells = make_cells(l, r, bound, parallelism=None if dealt else min(tasks, len(only)) if only is not None else tasks, counts=counts if only is None else (len(named(0)), len(named(1))))
    place = F.concat_ws(":", "left_batch", "right_batch")
    listed = lambda pairs: place.isin([f"{a}:{b}" for a, b in pairs])
    if only is not None:
        return cells.where(listed(only))
    return cells.where(~listed(skip)) if skip else cells


def _index(left, right, profiles, style, order, keep=None):
    return tuple(indexed(rows, style.counter, buckets_for(p.rows), order, keep=keep) for rows, p in zip((left, right), profiles))


def _grouped_cells(left: DataFrame, right: DataFrame, on: str, sizes: tuple[int, int], profiles, style: PromptStyle, scratch: Scratch) -> DataFrame:
    """Cells of rows whose ``on`` may be equal: groups are dealt whole to as many bins as full batches make, and a bin's batches meet.

    The number of cells grows with the rows, not with the product of both sides; a group larger than a batch has several.
    """
    bins = max(1, *(-(-p.rows // b) for p, b in zip(profiles, sizes)))
    binned = lambda rows: rows.where(F.col(on).isNotNull()).withColumn("bin", F.pmod(F.xxhash64(on), F.lit(bins)))
    l, r = (scratch.table(make_batches(binned(rows), size, style.counter, by="bin"), "batches") for rows, size in zip((left, right), sizes))  # noqa: E741
    cells = make_cells(l, r, on="bin")
    return cells.select(F.xxhash64("bin", "left_batch").alias("left_batch"), F.xxhash64("bin", "right_batch", F.lit(1)).alias("right_batch"), "left_items", "right_items")


def block_join(left: DataFrame, right: DataFrame, predicate: SemanticPredicate, model, batch_left: int, batch_right: int, style: PromptStyle | None = None, on_overflow: str = "fail", completion_check: str | None = None, order: str = "hash", parallelism: int | None = None, profiles: tuple[TableProfile, TableProfile] | None = None, plan: BatchPlan | None = None, method: str = "block", max_fee: float | None = None, resume: str | None = None, cache=None, on: str | None = None) -> JoinRun:
    """One prompt per pair of batches.  ``on_overflow``: fail (error), report (round says so), keep (complete cells only).

    With ``on`` rows match only where that column is equal, and cells are formed within groups.
    """
    began, style, run_id = time.perf_counter(), style or PromptStyle(), _new_run(method)
    scratch = Scratch(left.sparkSession, run_id, resume)
    profiles = profiles or profile_tables(left, right, style.counter, style.row_overhead)
    if max_fee is not None:
        n, m = (p.rows for p in profiles)
        nl, nr = -(-n // batch_left), -(-m // batch_right)
        width = width_of_match(style, profiles)
        written = (plan.estimate * n * m * width if plan else 0) + nl * nr
        check_fee(model, nl * nr * style.instruction_tokens(predicate.text) + nr * n * profiles[0].width_mean + nl * m * profiles[1].width_mean, written, max_fee)
    check = completion_check or ("stop_reason" if model.profile.stop_word else "text")
    if on is None:
        cells = _cells(_index(left, right, profiles, style, order), (batch_left, batch_right), profiles, tasks_for(left, model, parallelism))
    else:
        cells = _grouped_cells(left, right, on, (batch_left, batch_right), profiles, style, scratch)
        cells = cells.repartition(max(tasks_for(left, model, parallelism), sum(p.rows for p in profiles) // 5000), "left_batch", "right_batch")
    asked = ask_cached(cells, model, predicate.text, style, "block", cache, scratch) if cache else ask(cells, model, predicate.text, style, "block")
    answers = scratch.table(asked, "answers")
    complete = parse.is_complete(F.col("answer"), F.col("stopped"), check)
    calls, cut = answers.agg(F.count("*"), F.count_if(~complete)).first()
    found = _resolve(answers.where(complete), style, left, right)
    if on is not None:  # other groups share a bin, and a model may err across them
        found = _within(found, left, right, on)
    run = JoinRun(run_id, method, found, ledger_of(answers, run_id, 0, ~complete), plan, [Round(0, plan.estimate if plan else math.nan, batch_left, batch_right, calls, cut > 0)], time.perf_counter() - began)
    if cut and on_overflow == "fail":
        raise OverflowSignal(cut, run)
    return run


def packed_join(left: DataFrame, right: DataFrame, predicate: SemanticPredicate, model, limit_left: int, limit_right: int, style: PromptStyle | None = None, parallelism: int | None = None, on_overflow: str = "fail") -> JoinRun:
    """A block join whose batches hold so many tokens, not rows: prompts are alike in size whatever the widths."""
    began, style, run_id = time.perf_counter(), style or PromptStyle(), _new_run("packed")
    scratch = Scratch(left.sparkSession, run_id)
    profiles = profile_tables(left, right, style.counter)
    both = [scratch.table(pack_batches(rows, limit, style.counter, buckets_for(p.rows)), "batches") for rows, limit, p in zip((left, right), (limit_left, limit_right), profiles)]
    cells = make_cells(*both, _bytes_bound(profiles[1]), parallelism=tasks_for(left, model, parallelism), counts=tuple(b.count() for b in both))
    answers = scratch.table(ask(cells, model, predicate.text, style, "block"), "answers")
    complete = parse.is_complete(F.col("answer"), F.col("stopped"), "stop_reason" if model.profile.stop_word else "text")
    cut = answers.where(~complete).count()
    run = JoinRun(run_id, "packed", _resolve(answers.where(complete), style, left, right), ledger_of(answers, run_id, 0, ~complete), seconds=time.perf_counter() - began)
    if cut and on_overflow == "fail":
        raise OverflowSignal(cut, run)
    return run


def _resolve(answers: DataFrame, style: PromptStyle, left: DataFrame, right: DataFrame) -> DataFrame:
    if style.answer_form == "positions":
        return parse.parse_pairs(answers)
    # Rows as they stand come back as texts, and are found again by them.
    line = answers.select(F.explode(F.split("answer", "\n")).alias("line")).where("line <> '' and line <> 'DONE'")
    # Texts may hold the mark between them, so every place of it is tried; only real rows are found.
    parts = line.select(F.split("line", r" \| ", -1).alias("p")).where("size(p) > 1").withColumn("k", F.explode(F.sequence(F.lit(1), F.size("p") - 1)))
    both = parts.select(F.array_join(F.slice("p", F.lit(1), F.col("k")), " | ").alias("a"), F.array_join(F.slice("p", F.col("k") + 1, F.size("p") - F.col("k")), " | ").alias("b")).distinct()
    one = lambda df, name, text: df.select(F.col("row_id").alias(name), F.trim(F.regexp_replace("text", r"\s+", " ")).alias(text))
    return both.join(one(left, "left_id", "a"), "a").join(one(right, "right_id", "b"), "b").select("left_id", "right_id")


def width_of_match(style: PromptStyle, profiles: tuple[TableProfile, TableProfile]) -> float:
    """Tokens of a reported pair: two numbers, or both rows."""
    return WIDTH_MATCH if style.answer_form == "positions" else profiles[0].width_mean + profiles[1].width_mean + 1


def budget_of(model, condition: str, style: PromptStyle) -> int:
    """Tokens for rows and pairs of a call: the limit less the instructions and the terminator."""
    return model.profile.limit - style.instruction_tokens(condition) - 1


def fitting(left: DataFrame, right: DataFrame, predicate: SemanticPredicate, model, policy: str = "error", style: PromptStyle | None = None) -> tuple[DataFrame, DataFrame]:
    """Both sides with rows that half a call's budget holds; see ``oversize`` for what happens to wider ones.

    With ``chunk`` a row stands for its windows, under ids of their own; ``whole_rows`` takes pairs back.
    """
    style = style or PromptStyle()
    room = max(1, budget_of(model, predicate.text, style) // 2 - WIDTH_MATCH - style.row_overhead)
    out = []
    for rows in (left, right):
        fit = oversize(rows, room, policy, style.counter)
        if policy == "chunk":
            last = fit.agg(F.max("chunk")).first()[0] or 0
            keys = rows.select("row_id", "key")
            fit = fit.drop("key").join(keys, "row_id").select((F.col("row_id") * (last + 1) + F.col("chunk")).alias("row_id"), "text", "key", F.lit(last + 1).alias("stride"))
        out.append(fit)
    return out[0], out[1]


def whole_rows(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Pairs of rows of pairs of their windows, as ``fitting`` numbered them."""
    key = lambda rows, s: rows.select(F.col("row_id").alias(f"{s}_id"), F.floor(F.col("row_id") / F.col("stride")).cast("long").alias(f"{s}_row"))
    both = pairs.join(key(left, "left"), "left_id").join(key(right, "right"), "right_id")
    return both.select(F.col("left_row").alias("left_id"), F.col("right_row").alias("right_id")).distinct()


def plan_join(left: DataFrame, right: DataFrame, predicate: SemanticPredicate, model, estimate: float, style: PromptStyle | None = None, clamp: bool = True, profiles=None) -> tuple[BatchPlan, tuple[TableProfile, TableProfile]]:
    style = style or PromptStyle()
    profiles = profiles or profile_tables(left, right, style.counter, style.row_overhead)
    return optimal_batches(*profiles, estimate, budget_of(model, predicate.text, style), style.instruction_tokens(predicate.text), width_of_match(style, profiles), model.profile.write_ratio, clamp), profiles


def block_join_planned(left: DataFrame, right: DataFrame, predicate: SemanticPredicate, model, estimate: float = 1.0, style: PromptStyle | None = None, clamp: bool = True, **options) -> JoinRun:
    """Block join with sizes for an estimate: 1 is the conservative baseline, the true selectivity the informed one."""
    plan, profiles = plan_join(left, right, predicate, model, estimate, style, clamp)
    return block_join(left, right, predicate, model, plan.batch_left, plan.batch_right, style, profiles=profiles, plan=plan, **options)


def explain_join(left: DataFrame, right: DataFrame, predicate: SemanticPredicate, model, estimate: float = 1.0, growth: float = 4.0, style: PromptStyle | None = None) -> dict:
    """What a run would do and cost; no model is called."""
    plan, (a, b) = plan_join(left, right, predicate, model, estimate, style)
    rounds = max(0, math.ceil(math.log(1 / estimate) / math.log(growth))) if 0 < estimate < 1 else 0
    return {"rows": (a.rows, b.rows), "widths": (a.width_mean, b.width_mean), "batches": (plan.batch_left, plan.batch_right), "calls": plan.expected_calls, "fee_cents": plan.expected_cost * model.profile.read_price / 1000, "most_rounds": rounds + 1}


def _step(n: int) -> int:
    """A stride without a common divisor with n: cells are taken in an order that mixes both sides."""
    s = max(1, int(n * 0.6180339887))
    while math.gcd(s, n) != 1:
        s += 1
    return s


class _Adaptive:
    def __init__(self, left, right, predicate, model, growth, style, order, parallelism, max_fee, check, resume, part_cells, cache, on=None):
        self.on = on
        self.left, self.right, self.predicate, self.model, self.growth = left, right, predicate, model, growth
        self.style, self.max_fee, self.part_cells, self.cache = style, max_fee, part_cells, cache
        self.tasks = tasks_for(left, model, parallelism)
        self.check = check or ("stop_reason" if model.profile.stop_word else "text")
        self.run_id = _new_run("adaptive")
        self.scratch = Scratch(left.sparkSession, self.run_id, resume)
        self.profiles = profile_tables(left, right, style.counter, style.row_overhead)
        self.budget = budget_of(model, predicate.text, style)
        self.width = width_of_match(style, self.profiles)
        self.ledger, self.rounds, self.spent, self.order = [], [], 0.0, order
        self._sides = None

    @property
    def sides(self):
        """Both sides with their row numbers, written once; every round cuts its batches from them."""
        if self._sides is None:
            self._sides = _index(self.left, self.right, self.profiles, self.style, self.order, lambda x: self.scratch.table(x, "rows"))
        return self._sides

    def plan(self, estimate: float, widest: bool = False) -> BatchPlan:
        sides = [replace(p, width_mean=float(p.width_max)) for p in self.profiles] if widest else self.profiles
        return optimal_batches(*sides, estimate, self.budget, self.style.instruction_tokens(self.predicate.text), self.width, self.model.profile.write_ratio)

    def ask(self, cells: DataFrame, number: int, few: bool = False) -> tuple[DataFrame, int, int]:
        """Answers with ``complete``; how many calls, how many cut off.  ``few`` answers are kept as values."""
        what = (cells, self.model, self.predicate.text, self.style, "block")
        got = ask_cached(*what, self.cache, self.scratch) if self.cache else ask(*what)
        if few and not self.scratch.resume:
            rows = got.collect()  # at most the eight cells of a probe
            answers = self.left.sparkSession.createDataFrame(rows, got.schema)
            done = parse.complete_value(self.check)
            calls, cut = len(rows), sum(not done(x["answer"], x["stopped"]) for x in rows)
            read, written = sum(x["tokens_read"] for x in rows), sum(x["tokens_written"] for x in rows)
            answers = answers.withColumn("complete", parse.is_complete(F.col("answer"), F.col("stopped"), self.check))
        else:
            answers = self.scratch.table(got, "answers")
            answers = answers.withColumn("complete", parse.is_complete(F.col("answer"), F.col("stopped"), self.check))
            calls, cut, read, written = answers.agg(F.count("*"), F.count_if(~F.col("complete")), F.sum("tokens_read"), F.sum("tokens_written")).first()
        self.ledger.append(ledger_of(answers, self.run_id, number, ~F.col("complete")))
        m = self.model.profile
        self.spent += ((read or 0) * m.read_price + (written or 0) * m.write_price) / 1000
        if self.max_fee is not None and self.spent > self.max_fee:
            raise FeeLimit(f"{self.spent:.2f} cents were spent, {self.max_fee} allowed")
        return answers, calls, cut

    def waves(self, plan: BatchPlan, number: int, probe: str, stop: bool) -> tuple[list[DataFrame], int]:
        """All cells of a plan, first 1, 2, 4, ... of them; ends at an overflow if ``stop``.

        The cells of a probe are named here, so that only their batches are formed; the rest follows in parts of
        ``part_cells`` (each is kept when a run is resumed).
        """
        sizes = (plan.batch_left, plan.batch_right)
        nl, nr = (max(1, -(-p.rows // b)) for p, b in zip(self.profiles, sizes))
        n = nl * nr
        # Rank k is that of cell k * inverse (mod n), an order that mixes both sides.
        inverse = pow(_step(n), -1, n) if n > 1 else 0
        probed = [divmod(k * inverse % n, nr) for k in range(min(n, PROBES))] if probe == "doubling" else []
        parts, total, cut, at = [], 0, 0, 0
        while at < len(probed):
            some = probed[at : 2 * at + 1]
            at += len(some)
            answers, calls, bad = self.ask(_cells(self.sides, sizes, self.profiles, self.tasks, only=some), number, few=True)
            parts.append(answers)
            total, cut = total + calls, cut + bad
            if bad and stop:
                break
        if at < n and not (cut and stop):
            cells = _cells(self.sides, sizes, self.profiles, self.tasks, skip=probed)
            pieces = max(1, math.ceil(n / self.part_cells)) if self.part_cells else 1
            for k in range(pieces):
                mine = cells.where(F.pmod(F.xxhash64("left_batch", "right_batch"), F.lit(pieces)) == k) if pieces > 1 else cells
                answers, calls, bad = self.ask(mine, number)
                parts.append(answers)
                total, cut = total + calls, cut + bad
                if bad and stop:
                    break
        self.rounds.append(Round(number, plan.estimate, *sizes, total, cut > 0))
        return parts, cut

    def whole(self, estimate: float, probe: str) -> DataFrame:
        """Everything is asked again after an overflow."""
        number, widest = 0, False
        while True:
            plan = self.plan(estimate, widest)
            parts, cut = self.waves(plan, number, probe, stop=True)
            if not cut:
                return _union(parts)
            if (plan.batch_left, plan.batch_right) == (1, 1):
                raise BudgetTooSmall("a single pair doesn't fit a call")
            if estimate >= 1:
                if widest:
                    raise BudgetTooSmall("batches for the widest rows overflow")
                widest = True
            estimate, number = min(1.0, estimate * self.growth), number + 1

    def failed(self, estimate: float, probe: str) -> DataFrame:
        """Only cells that overflowed are asked again, split by the new sizes."""
        plan = self.plan(estimate)
        sizes, number = (plan.batch_left, plan.batch_right), 0
        if self.on is None:
            parts, cut = self.waves(plan, 0, probe, stop=False)
            both = _cells(self.sides, sizes, self.profiles, self.tasks)
        else:
            both = _grouped_cells(self.left, self.right, self.on, sizes, self.profiles, self.style, self.scratch)
            both = self.scratch.table(both.repartition(max(self.tasks, sum(p.rows for p in self.profiles) // 5000), "left_batch", "right_batch"), "cells")
            answers, calls, cut = self.ask(both, 0)
            parts = [answers]
            self.rounds.append(Round(0, estimate, *sizes, calls, cut > 0))
        done = [p.where("complete") for p in parts]
        again = _union(parts).where("not complete").select("left_batch", "right_batch")
        cells = self.scratch.table(both.join(F.broadcast(again) if cut <= 100_000 else again, ["left_batch", "right_batch"], "left_semi"), "cells") if cut else None
        while cut:
            if sizes == (1, 1):
                raise BudgetTooSmall("a single pair doesn't fit a call")
            number, estimate = number + 1, min(1.0, estimate * self.growth)
            new = self.plan(estimate)
            smaller = (min(sizes[0], new.batch_left), min(sizes[1], new.batch_right))
            sizes = smaller if smaller != sizes else tuple(max(1, s // 2) for s in sizes)
            cells = self.scratch.table(_split(cells, *sizes).repartition(max(self.tasks, -(-cut // 1000)), "left_batch", "right_batch"), "cells")
            answers, calls, cut = self.ask(cells, number)
            self.rounds.append(Round(number, estimate, *sizes, calls, cut > 0))
            done.append(answers.where("complete"))
            cells = cells.join(answers.where("not complete").select("left_batch", "right_batch"), ["left_batch", "right_batch"], "left_semi")
        return _union(done)


def _split(cells: DataFrame, a: int, b: int) -> DataFrame:
    """Cells cut to at most a x b rows, under new numbers."""
    cut = lambda items, k: F.explode(F.transform(F.sequence(F.lit(0), F.floor((F.size(items) - 1) / k).cast("int")), lambda i: F.struct(i.alias("i"), F.slice(items, i * k + 1, F.lit(k)).alias("items"))))
    c = cells.withColumn("l", cut(F.col("left_items"), a)).withColumn("r", cut(F.col("right_items"), b))
    return c.select(F.xxhash64("left_batch", "right_batch", "l.i").alias("left_batch"), F.xxhash64("left_batch", "right_batch", "r.i", F.lit(1)).alias("right_batch"), F.col("l.items").alias("left_items"), F.col("r.items").alias("right_items"))


def adaptive_join(left: DataFrame, right: DataFrame, predicate: SemanticPredicate, model, start_estimate: float, growth: float = 4.0, restart: str = "all", direction: str = "up", probe: str = "doubling", style: PromptStyle | None = None, order: str = "hash", parallelism: int | None = None, max_fee: float | None = None, completion_check: str | None = None, resume: str | None = None, part_cells: int | None = None, cache=None, on: str | None = None) -> JoinRun:
    """Block joins for a rising selectivity estimate, until no answer is cut off.

    With ``on``, a column of both sides, rows match only where it is equal: cells are formed within groups, all at once
    (``probe`` plays no part), and those that overflow are split (``restart="failed"``).

    ``resume`` is a folder in which finished parts are kept: the same call after a lost driver takes their answers
    from there and pays for the others only (``part_cells`` cells a part).  Arguments or tables that differ raise.
    ``cache`` is an ``AnswerCache``: what any run has recorded there is not asked again.
    """
    if growth <= 1:
        raise ValueError("growth must exceed 1")
    if not 0 < start_estimate <= 1:
        raise ValueError("the estimate must be above 0 and at most 1")
    if restart not in ("all", "failed"):
        raise ValueError(f"unknown restart policy {restart!r}")
    if probe not in ("doubling", "none"):
        raise ValueError(f"unknown probe {probe!r}")
    if on is not None and (restart != "failed" or direction != "up" or resume or part_cells):
        raise ValueError("an equal key goes with restart 'failed' and the upward direction, without resume")
    began = time.perf_counter()
    style = style or PromptStyle()
    if direction == "down":
        if restart != "all" or probe != "doubling" or resume:
            raise ValueError("restart, probe and resume belong to the upward direction")
        return _downward(left, right, predicate, model, start_estimate, growth, style, order, began, parallelism, max_fee, completion_check)
    if direction != "up":
        raise ValueError(f"unknown direction {direction!r}")
    a = _Adaptive(left, right, predicate, model, growth, style, order, parallelism, max_fee, completion_check, resume, part_cells, cache, on)
    spark = left.sparkSession
    if not (a.profiles[0].rows and a.profiles[1].rows):
        return JoinRun(a.run_id, "adaptive", spark.createDataFrame([], schemas.PAIR), spark.createDataFrame([], schemas.LEDGER), None, [], time.perf_counter() - began)
    if resume:
        says = repr((predicate.text, style, model.profile, start_estimate, growth, restart, probe, order, completion_check, part_cells, a.profiles))
        kept = a.scratch.table(spark.createDataFrame([(says,)], "says string"), "arguments").first()["says"]
        if kept != says:
            raise ValueError("the folder to resume from belongs to another call")
    if max_fee is not None and (fee := a.plan(start_estimate).expected_cost * model.profile.read_price / 1000) > max_fee:
        raise FeeLimit(f"{fee:.2f} cents are forecast, {max_fee} allowed")
    answers = a.whole(start_estimate, probe) if restart == "all" else a.failed(start_estimate, probe)
    if on is not None:  # other groups share a bin, and a model may err across them
        answers_on = _within(_resolve(answers, style, left, right), left, right, on)
    last = a.rounds[-1]
    plan = BatchPlan(last.batch_left, last.batch_right, last.estimate, a.budget, last.calls, math.nan, math.nan, math.nan)
    return JoinRun(a.run_id, "adaptive", answers_on if on is not None else _resolve(answers, style, left, right), _union(a.ledger), plan, a.rounds, time.perf_counter() - began)


def _downward(left, right, predicate, model, estimate, growth, style, order, began, parallelism, max_fee, completion_check, parts: int = 4) -> JoinRun:
    """Starts high and lowers the estimate to what finished slices show; overflow raises it again."""
    run_id, pairs, ledger, rounds, spent = _new_run("adaptive_down"), [], [], [], 0.0
    n_right = right.count()
    for k in range(parts):
        part = left.where(F.pmod(F.xxhash64("row_id"), F.lit(parts)) == k)
        n, widest = part.count(), False
        while n and n_right:
            plan, profiles = plan_join(part, right, predicate, model, estimate, style)
            if widest:
                plan, _ = plan_join(part, right, predicate, model, estimate, style, profiles=tuple(replace(p, width_mean=float(p.width_max)) for p in profiles))
            if max_fee is not None and (fee := spent + plan.expected_cost * model.profile.read_price / 1000) > max_fee:
                raise FeeLimit(f"{fee:.2f} cents are forecast, {max_fee} allowed")
            run = block_join(part, right, predicate, model, plan.batch_left, plan.batch_right, style, "report", completion_check, order, parallelism, profiles, plan)
            spent += float(run.fees(model.profile).first()["fee"])
            ledger.append(run.ledger.withColumn("run_id", F.lit(run_id)).withColumn("round", F.lit(len(rounds))))
            rounds.append(replace(run.rounds[0], number=len(rounds)))
            if max_fee is not None and spent > max_fee:
                raise FeeLimit(f"{spent:.2f} cents were spent, {max_fee} allowed")
            if not run.rounds[0].overflow:
                pairs.append(run.pairs)
                estimate = min(estimate, max(growth * run.pairs.count() / (n * n_right), 1e-6))
                break
            if estimate >= 1 and widest:
                raise BudgetTooSmall("batches for the widest rows overflow")
            widest = estimate >= 1
            estimate = min(1.0, estimate * growth)
    spark = left.sparkSession
    return JoinRun(run_id, "adaptive_down", _union(pairs) if pairs else spark.createDataFrame([], schemas.PAIR), _union(ledger) if ledger else spark.createDataFrame([], schemas.LEDGER), None, rounds, time.perf_counter() - began)


def hybrid_join(left: DataFrame, right: DataFrame, on: str, predicate: SemanticPredicate, model, batch_left: int, batch_right: int, style: PromptStyle | None = None, parallelism: int | None = None, max_fee: float | None = None) -> JoinRun:
    """Equal ``on`` and the condition: the equal key blocks first, so cells exist within its groups only."""
    began, style, run_id = time.perf_counter(), style or PromptStyle(), _new_run("hybrid")
    scratch = Scratch(left.sparkSession, run_id)
    lb = scratch.table(make_batches(left.where(F.col(on).isNotNull()), batch_left, style.counter, by=on), "left")
    rb = scratch.table(make_batches(right.where(F.col(on).isNotNull()), batch_right, style.counter, by=on), "right")
    if max_fee is not None:
        per = lambda b, s: b.groupBy(on).agg(F.count("*").alias(f"n{s}"), F.sum(F.col("tokens") + F.size("items") * style.row_overhead).alias(f"w{s}"))
        n, read = per(lb, 1).join(per(rb, 2), on).agg(F.coalesce(F.sum(F.expr("n1 * n2")), F.lit(0)), F.coalesce(F.sum(F.expr("n2 * w1 + n1 * w2")), F.lit(0))).first()
        check_fee(model, n * style.instruction_tokens(predicate.text) + read, n, max_fee)
    cells = make_cells(lb, rb, on=on)
    cells = cells.select(F.xxhash64(on, "left_batch").alias("left_batch"), F.xxhash64(on, "right_batch", F.lit(1)).alias("right_batch"), "left_items", "right_items")
    answers = scratch.table(ask(cells, model, predicate.text, style, "block", tasks_for(left, model, parallelism)), "answers")
    cut = answers.where("not stopped").count()
    run = JoinRun(run_id, "hybrid", _resolve_within(answers, style, left, right, on), ledger_of(answers, run_id, 0, ~F.col("stopped")), seconds=time.perf_counter() - began)
    if cut:
        raise OverflowSignal(cut, run)
    return run


def _resolve_within(answers: DataFrame, style: PromptStyle, left: DataFrame, right: DataFrame, on: str) -> DataFrame:
    """As ``_resolve``; texts that are found again count with an equal ``on`` only."""
    pairs = _resolve(answers, style, left, right)
    return pairs if style.answer_form == "positions" else _within(pairs, left, right, on)


def _within(pairs: DataFrame, left: DataFrame, right: DataFrame, on: str) -> DataFrame:
    """Pairs with an equal ``on``."""
    key = lambda rows, name: rows.select(F.col("row_id").alias(name), F.col(on).alias(f"{name}_on"))
    return pairs.join(key(left, "left_id"), "left_id").join(key(right, "right_id"), "right_id").where("left_id_on = right_id_on").select("left_id", "right_id")


def semantic_filter(rows: DataFrame, predicate: SemanticPredicate, model, size: int, style: PromptStyle | None = None, parallelism: int | None = None, max_fee: float | None = None) -> JoinRun:
    """Rows of one table that meet the condition, as pairs.left_id."""
    began, style, run_id = time.perf_counter(), style or PromptStyle(), _new_run("filter")
    scratch = Scratch(rows.sparkSession, run_id)
    p, _ = profile_tables(rows, rows.limit(0), style.counter, style.row_overhead)
    calls = -(-p.rows // size)
    check_fee(model, calls * style.instruction_tokens(predicate.text, "single") + p.rows * p.width_mean, calls, max_fee)
    n = max(1, min(calls, max(tasks_for(rows, model, parallelism), calls // 1000)))
    many = calls >= MANY * n
    batches = make_batches(rows, size, style.counter, buckets_for(p.rows), tasks=n if many else None)
    if not many:
        batches = batches.repartitionById(n, F.pmod(F.col("batch_id"), F.lit(n)).cast("int"))
    cells = batches.select(F.col("batch_id").alias("left_batch"), F.lit(0).cast("long").alias("right_batch"), F.col("items").alias("left_items"), F.slice("items", 1, 0).alias("right_items"))
    answers = scratch.table(ask(cells, model, predicate.text, style, "single"), "answers")
    if cut := answers.where("not stopped").count():
        raise OverflowSignal(cut, JoinRun(run_id, "filter", answers, answers))
    at = F.explode(F.array_distinct(F.regexp_extract_all("answer", F.lit(r"(\d+);"), F.lit(1))))
    found = answers.select("left_ids", at.alias("x")).select(F.try_element_at("left_ids", F.col("x").try_cast("int")).alias("left_id")).where("left_id is not null")
    return JoinRun(run_id, "filter", found, ledger_of(answers, run_id, 0, ~F.col("stopped")), seconds=time.perf_counter() - began)


def with_distinct_texts(join, left: DataFrame, right: DataFrame, *args, **options) -> JoinRun:
    """Runs a join on distinct (text, key) only and gives its pairs to all rows that have them."""
    def classes(rows):
        c = rows.groupBy("text", "key").agg(F.min("row_id").alias("row_id"))
        m = rows.alias("a").join(c.alias("c"), (F.col("a.text") == F.col("c.text")) & F.col("a.key").eqNullSafe(F.col("c.key"))).select(F.col("a.row_id").alias("row_id"), F.col("c.row_id").alias("rep"))
        return c.select("row_id", "text", "key"), m

    (l, lm), (r, rm) = classes(left), classes(right)
    run = join(l, r, *args, **options)
    a = lm.select(F.col("rep").alias("left_id"), F.col("row_id").alias("left_row"))
    b = rm.select(F.col("rep").alias("right_id"), F.col("row_id").alias("right_row"))
    run.pairs = run.pairs.join(a, "left_id").join(b, "right_id").select(F.col("left_row").alias("left_id"), F.col("right_row").alias("right_id"))
    return run


def oversize(rows: DataFrame, limit: int, policy: str = "error", counter: str = "words") -> DataFrame:
    """Rows wider than a budget: an error, cut, or (``chunk``) windows with half overlap under (row_id, chunk)."""
    from semjoin.functions import tokens

    if policy == "cut":
        return rows.withColumn("text", tokens.cut_column(F.col("text"), limit))
    if policy == "chunk":
        return tokens.chunks(rows, limit, limit // 2)
    if rows.where(count_column(F.col("text"), counter) > limit).isEmpty():
        return rows
    raise BudgetTooSmall(f"some rows have more than {limit} tokens")
