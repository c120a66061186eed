"""Cloze templates, label words and the class score of the mask slot."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, functions as F

from pairmatch.functions.serialize import MASK

# Label words of the general relation, and the pair used for comparison.
GENERAL_YES, GENERAL_NO = ("matched", "similar", "relevant"), ("mismatched", "different", "irrelevant")
SIMPLE_YES, SIMPLE_NO = ("matched",), ("mismatched",)


@dataclass(frozen=True)
class Verbalizer:
    yes: tuple[str, ...] = GENERAL_YES
    no: tuple[str, ...] = GENERAL_NO

    @staticmethod
    def general() -> Verbalizer:
        return Verbalizer()

    @staticmethod
    def simple() -> Verbalizer:
        return Verbalizer(SIMPLE_YES, SIMPLE_NO)

    @property
    def vocabulary(self) -> tuple[str, ...]:
        """Union of the class sets, in order; positions index the slot's distribution."""
        return tuple(dict.fromkeys(self.yes + self.no))


@dataclass(frozen=True)
class Relation:
    """A binary relation is what its label words and labels make of it."""

    name: str
    words: Verbalizer = Verbalizer()


@dataclass(frozen=True)
class Template:
    """shape "t1" (slot after both records) or "t2" (slot between them); kind "hard" or "soft" with k learned tokens a place."""

    shape: str = "t2"
    kind: str = "hard"
    k: int = 3

    def layout(self) -> list[str]:
        """left, right, slot, and the literal words or learned places between them, in order."""
        words = {"t1": ["left", "right", "They", "are", "slot"], "t2": ["left", "is", "slot", "to", "right"]}[self.shape]
        if self.kind == "hard":
            return words
        out, n = [], 0
        for w in words:
            if w in ("left", "right", "slot"):
                out.append(w)
            else:
                out += [f"[P{n + i}]" for i in range(self.k)]
                n += self.k
        return out

    def apply(self, left: Column, right: Column) -> Column:
        return F.concat_ws(" ", *[{"left": left, "right": right, "slot": F.lit(MASK)}.get(w, F.lit(w)) for w in self.layout()])

    def slot_position(self, left: Column, right: Column) -> Column:
        """0-based token position of the slot."""
        n, count = F.lit(0), {"left": left, "right": right}
        for w in self.layout():
            if w == "slot":
                return n
            n = n + (F.size(F.split(count[w], " ")) if w in count else 1)
        raise ValueError("no slot")


def class_scores(word_p: Column, verb: Verbalizer, normalize: bool = True) -> tuple[Column, Column]:
    """(no, yes): mean slot probability of the class's words; over their sum if normalised."""
    at = {w: i for i, w in enumerate(verb.vocabulary)}
    mean = lambda words: reduce(lambda x, y: x + y, [word_p[at[w]] for w in words]) / len(words)
    no, yes = mean(verb.no), mean(verb.yes)
    return (no / (no + yes), yes / (no + yes)) if normalize else (no, yes)
