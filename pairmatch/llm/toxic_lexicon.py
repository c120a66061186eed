"""Toxicity by a weighted lexicon that an Aho-Corasick automaton matches.

Texts are folded first: lower case, look-alike letters of other scripts and digits or
signs that stand for letters become plain letters, other signs become spaces. The
lexicon holds word beginnings with log-odds weights, learnt from labelled rows: the
shortest beginning that is rare in clean text, lengthened while it loses few toxic
documents. A hit inside an exception phrase does not count. The weight found is set
against the text's length and calibrated to a score.

The labelled rows used are at most `per_class` of each class, lowest by hash of the id,
of the longer ones `parts` pieces, dealt evenly from first to last; texts that are equal
when folded count once. Scoring reads whole texts.

Defined results: null and empty texts have weight 0 and so the lowest score; null
labels, and labels without a document, are not used; an empty lexicon scores all
documents alike; repeated rows are scored each, alike; an empty table gives no row.
"""

from __future__ import annotations

import math
import re
from collections import Counter

from pyspark.sql import Column, DataFrame, functions as F

from pairmatch.llm.common import fit_logistic, lean, sigmoid
from pairmatch.llm.quality_zstd import labelled_sample

# Look-alikes of Latin letters, and signs written for letters.
HOMOGLYPHS = {
    "а": "a", "в": "b", "с": "c", "е": "e", "н": "h", "і": "i", "ј": "j", "к": "k", "м": "m", "о": "o",
    "р": "p", "ѕ": "s", "т": "t", "у": "y", "х": "x", "ԁ": "d", "ԛ": "q", "ԝ": "w", "α": "a", "β": "b",
    "ε": "e", "ι": "i", "κ": "k", "ν": "v", "ο": "o", "ρ": "p", "τ": "t", "υ": "u", "χ": "x", "ı": "i",
}
SIGNS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s"}

SHORTEST, LONGEST = 4, 12


def _table() -> dict[int, str]:
    fold = {i: " " for i in range(128) if not chr(i).isalnum()}
    fold |= {0xFF01 + i: chr(0x21 + i).lower() for i in range(94) if chr(0x21 + i).isalnum()}  # full-width forms
    fold |= {ord(k): v for k, v in (HOMOGLYPHS | SIGNS).items()}
    return fold | {0x200B: "", 0x200C: "", 0x200D: "", 0xAD: "", 0xA0: " "}


FOLD = _table()


def fold(text: str) -> str:
    return " " + text.lower().translate(FOLD) + " "


class Lexicon:
    def __init__(self, weights: dict[str, float], exceptions: tuple[str, ...] = (), slope: float = 1.0, bias: float = 0.0):
        self.weights, self.exceptions, self.slope, self.bias = weights, tuple(exceptions), slope, bias

    def automaton(self):
        """Both lexicon entries and exception phrases, told apart by their value."""
        import ahocorasick

        a = ahocorasick.Automaton()
        for w, x in self.weights.items():
            a.add_word(" " + w, (len(w), x))
        for p in self.exceptions:
            a.add_word(" " + p + " ", (len(p) + 1, None))
        if len(a):
            a.make_automaton()
            return a
        return None

    @staticmethod
    def found(text: str, automaton) -> float:
        """Summed weight of the hits outside exception phrases."""
        if automaton is None:
            return 0.0
        total, hits, spare = 0.0, [], []
        for end, (n, weight) in automaton.iter(text):
            if weight is None:
                spare.append((end - n, end))
            else:
                hits.append((end - n, end, weight))
        reach, rest = 0, sorted(spare, reverse=True)  # phrases by where they begin; the furthest end of those begun
        for a, b, weight in sorted(hits):
            while rest and rest[-1][0] <= a:
                reach = max(reach, rest.pop()[1])
            if b > reach:
                total += weight
        return total

    def feature(self, text: str, automaton) -> float:
        folded = fold(text)
        weight = self.found(folded, automaton)
        return math.log1p(100.0 * weight / (100.0 + math.sqrt(len(folded)))) if weight else 0.0

    def score(self, feature):
        return sigmoid(self.slope * feature + self.bias)


def learn_lexicon(sample: list, exceptions: tuple[str, ...] = (), precision: float = 0.9, support: int = 8) -> Lexicon:
    """sample: [(text, or its pieces; toxic)]; exceptions: phrases, besides those that are learnt."""
    import numpy as np

    sample = [(t if isinstance(t, str) else "".join(t), y) for t, y in sample]
    folded = list(dict.fromkeys((fold(t), y) for t, y in sample))  # copies of one text must not vouch for its words
    size = Counter(y for _, y in folded)
    least = max(support, 0.02 * size[1])
    seen: dict[int, Counter] = {0: Counter(), 1: Counter()}
    frequent = None  # beginnings of the last length that enough toxic documents have; only these are lengthened
    for n in range(SHORTEST, LONGEST + 1):
        level: dict[int, Counter] = {0: Counter(), 1: Counter()}
        for t, y in folded:
            level[y].update({w[:n] for w in t.split() if len(w) >= n and (frequent is None or w[: n - 1] in frequent)})
        frequent = {w for w, k in level[1].items() if k >= least}
        for y in (0, 1):
            seen[y].update({w: level[y][w] for w in frequent if level[y][w]})
        if not frequent:
            break
    rate = lambda w, y: (seen[y][w] + (0.5 if y else 0.25)) / (size[y] + 1)
    telling = {w for w, n in seen[1].items() if n >= least and rate(w, 1) / (rate(w, 1) + rate(w, 0)) >= precision}
    longer: dict[str, list[str]] = {}
    for w in telling:
        longer.setdefault(w[:-1], []).append(w)
    weights: dict[str, float] = {}
    for w in sorted(telling, key=lambda w: (len(w), w)):
        if any(w[:n] in telling for n in range(SHORTEST, len(w))):
            continue
        while rest := [x for x in longer.get(w, []) if seen[1][x] >= 0.9 * seen[1][w]]:
            w = rest[0]
        weights[w] = math.log(rate(w, 1) / rate(w, 0))
    lexicon = Lexicon(weights, tuple(" ".join(fold(p).split()) for p in exceptions))
    phrases: dict[int, Counter] = {0: Counter(), 1: Counter()}
    starts = tuple(weights)
    for t, y in folded:
        words = t.split() if starts else []
        at = [i for i, w in enumerate(words) if w.startswith(starts)]
        phrases[y].update({" ".join(words[max(0, i - a) : i + b]) for i in at for a, b in ((1, 1), (0, 2))})
    lexicon.exceptions += tuple(sorted(p for p, n in phrases[0].items() if " " in p and n >= support and n * size[1] > 9 * phrases[1][p] * size[0]))
    automaton = lexicon.automaton()
    x = np.array([lexicon.feature(t, automaton) for t, _ in sample]) if sample else np.zeros(0)
    w, lexicon.bias = fit_logistic(x, np.array([y for _, y in sample])) if sample else (np.zeros(1), 0.0)
    lexicon.slope = float(w[0])
    return lexicon


def score_documents(docs: DataFrame, lexicon: Lexicon) -> DataFrame:
    """doc_id, feature, score of every document."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        automaton = lexicon.automaton()
        for batch in batches:
            x = np.array([lexicon.feature(t.as_py() or "", automaton) for t in batch.column(1)], float)
            yield pa.record_batch([batch.column(0), pa.array(x), pa.array(lexicon.score(x))], names=["doc_id", "feature", "score"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, feature double, score double")


def clean_documents(docs: DataFrame, lexicon: Lexicon, threshold: float = 0.7) -> DataFrame:
    """The rows that score under the threshold, all columns; null ids included."""
    names = docs.columns
    at = names.index("text")

    def run(batches):
        import pyarrow as pa

        automaton = lexicon.automaton()
        for batch in batches:
            keep = [lexicon.score(lexicon.feature(t.as_py() or "", automaton)) < threshold for t in batch.column(at)]
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)


def fitted_lexicon(docs: DataFrame, labels: DataFrame, learn: Column, per_class: int = 3000, parts: int = 8) -> Lexicon:
    return learn_lexicon(labelled_sample(docs, labels, "toxic", learn, per_class, parts))


def toxicity_scores(docs: DataFrame, labels: DataFrame, learn: Column) -> DataFrame:
    return score_documents(docs, fitted_lexicon(docs, labels, learn))
