"""Prompts: the wording is ours; rows are collapsed to one line and numbered."""

from __future__ import annotations

from dataclasses import dataclass

from semjoin.functions.parse import TERMINATOR
from semjoin.functions.tokens import count


@dataclass(frozen=True)
class PromptStyle:
    nudge: bool = True
    verbose: bool = False
    answer_form: str = "positions"  # or "rows"
    counter: str = "words"

    def _preface(self) -> str:
        if not self.verbose:
            return ""
        return (
            "You help with matching records. You get a statement about two passages and the passages themselves. "
            "Read both with care, take nothing for granted that they don't say, and weigh wording, names and dates before you settle. "
            "A statement that holds only in part doesn't hold. Give the verdict and no reasons for it, without any further remark.\n"
        )

    def pair(self, condition: str, left: str, right: str) -> str:
        return f"{self._preface()}Decide whether this holds for the two passages below: {condition}\nReply with one word, yes or no.\nFirst: {line(left)}\nSecond: {line(right)}\nReply:"

    def block(self, condition: str, left: list[str], right: list[str]) -> str:
        form = "A-number,B-number; and so on" if self.answer_form == "positions" else "both items as they stand, one combination a line"
        nudge = " Leave none out." if self.nudge else ""
        number = lambda rows: "".join(f"{i}) {line(t)}\n" for i, t in enumerate(rows, 1))
        return (
            f"{self._preface()}You get two numbered lists. Report each combination of one item of list A and one item of list B for which this holds: {condition}\n"
            f"Write {form}.{nudge} Close with {TERMINATOR}.\nList A:\n{number(left)}List B:\n{number(right)}Combinations:"
        )

    def single(self, condition: str, rows: list[str]) -> str:
        number = "".join(f"{i}) {line(t)}\n" for i, t in enumerate(rows, 1))
        return f"{self._preface()}You get a numbered list. Report each item for which this holds: {condition}\nWrite number; and so on. Close with {TERMINATOR}.\nList A:\n{number}Items:"

    def instruction_tokens(self, condition: str, kind: str = "block") -> int:
        """Tokens of the prompt without rows."""
        text = {"block": lambda: self.block(condition, [], []), "pair": lambda: self.pair(condition, "", ""), "single": lambda: self.single(condition, [])}[kind]()
        return count(text, self.counter)

    @property
    def row_overhead(self) -> int:
        """Tokens of a row's number."""
        return count("10) ", self.counter)


def line(text: str) -> str:
    return " ".join(text.split())
