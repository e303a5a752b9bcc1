"""The model protocol, and predicates as simulated models evaluate them."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from typing import Protocol

from semjoin.types import ModelProfile


@dataclass(frozen=True)
class Prompt:
    """``keys_*`` are hidden truth keys of the rows, by position; they cost no tokens."""

    text: str
    kind: str  # block, pair or single
    keys_left: tuple[str | None, ...] = ()
    keys_right: tuple[str | None, ...] = ()
    ids_left: tuple[int, ...] = ()
    ids_right: tuple[int, ...] = ()


@dataclass(frozen=True)
class Answer:
    text: str
    stopped: bool
    tokens_read: int
    tokens_written: int
    latency_ms: float


class LanguageModel(Protocol):
    """Picklable; ``complete`` runs on the executors."""

    profile: ModelProfile

    def complete(self, prompts: Iterable[Prompt]) -> Iterator[Answer]: ...


class Decision(Protocol):
    """What a condition means to a simulated model: the matching positions, in order."""

    def matches(self, left: list[tuple[str, str | None]], right: list[tuple[str, str | None]]) -> list[tuple[int, int]]: ...


@dataclass(frozen=True)
class SemanticPredicate:
    """A condition in plain language, with its meaning for simulated models."""

    text: str
    decision: Decision | None = None


@dataclass(frozen=True)
class SameFeature:
    """Rows match if their features are equal; features come from text and key, None matches nothing."""

    left: object
    right: object

    def matches(self, left, right):
        at: dict = {}
        for j, row in enumerate(right, 1):
            if (f := self.right(*row)) is not None:
                at.setdefault(f, []).append(j)
        return [(i, j) for i, row in enumerate(left, 1) if (f := self.left(*row)) is not None for j in at.get(f, ())]


@dataclass(frozen=True)
class EachPair:
    holds: object

    def matches(self, left, right):
        return [(i, j) for i, a in enumerate(left, 1) for j, b in enumerate(right, 1) if self.holds(a, b)]


@dataclass
class Latency:
    """Modelled milliseconds of a call."""

    fixed: float = 300.0
    read: float = 0.05
    write: float = 40.0
    extra: dict = field(default_factory=dict)

    def of(self, tokens_read: int, tokens_written: int) -> float:
        return self.fixed + self.read * tokens_read + self.write * tokens_written
