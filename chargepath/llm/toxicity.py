"""Toxicity by a weighted finite-state pattern grammar.

Five transducers read the words of a clause. The insult transducer runs over
letters: a trie of stems whose states carry weights (log-odds of the stem in
toxic against other labelled training documents). Threats, targets, negations
and words of reported speech are accepted as whole words. Three more machines
run over the classes of words: words since a target, words since a negation,
and whether speech is reported; they are composed into one product machine,
whose states are made on first use. The machine of targets runs from the right
as well, so a match knows the targets on both sides of it. A match weighs what
its stem or threat weighs, more with a target close by, less under negation or
reported speech; a clause's score is the sum of its matches. Each word is read
once from either side, however long a clause is. A logistic curve, fitted on
the same training rows, turns clause scores into a document score.

The model is fitted on at most ``max_train`` labelled documents, taken by the
order of a hash of their ids. Null and empty texts get the score of a text
without matched clauses; texts of any length are read whole; repeated rows get
equal scores; without any training row all scores are the prior; an empty table
gives no rows; of stems of equal claim the shorter, then the first by letters,
is kept; an output replaces a column of its name.
"""

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chargepath.llm.common import boxed, cut, unboxed

# Word classes of the grammar in four languages.
SEEDS = frozenset("idiot idiots moron morons stupid dumb scum trash loser losers pathetic worthless disgusting clown clowns fool fools imbecile vermin filth garbage bastard bitch idioten dumm dummkopf abschaum arschloch trottel imbecil estupido estúpido idiota basura escoria débile connard salaud ordure crétin".split())
THREATS = frozenset(
    "kill kills killing hurt destroy beat punish shoot stab strangle burn attack töten umbringen schlagen erschießen verprügeln vernichten tuer frapper détruire étrangler brûler matar golpear destruir disparar quemar".split())
TARGETS = frozenset("you your yours u he she him her they them these those du dich dir ihr euch sie tu te toi vous ils elles tú usted ustedes ellos ellas".split())
NEGATIONS = frozenset("not no never isn't aren't wasn't don't nobody nicht kein keine nie ne pas jamais nunca ni".split())
REPORTS = frozenset("said says called quoted quote reported claims wrote sagte sagt nannte dit disait appelé dijo llamó".split())
_WORD = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?")
_CLAUSE = re.compile(r"[.!?;:\n]+")


#: Bits of a word's class.
TARGET, NEGATION, REPORT, THREAT = 1, 2, 4, 8
#: Words between a match and a target, a threat and its target, a match and a negation before it.
NEAR_TARGET, THREAT_TARGET, NEAR_NEGATION = 4, 3, 3
#: What a target, a negation and reported speech make of a match's weight.
WITH_TARGET, NEGATED, REPORTED = 1.25, 0.6, 0.7


class Stems:
    """The insult transducer: a trie over letters; the weight of a word is the most that a state on its path carries."""

    def __init__(self, stems: dict[str, float]) -> None:
        self.next: list[dict[str, int]] = [{}]
        self.weight, self.at_end = [0.0], [0.0]
        for stem, weight in stems.items():
            state, whole = 0, stem.endswith("$")
            for letter in stem.removesuffix("$"):
                to = self.next[state].get(letter)
                if to is None:
                    to = self.next[state][letter] = len(self.next)
                    self.next.append({})
                    self.weight.append(0.0)
                    self.at_end.append(0.0)
                state = to
            held = self.at_end if whole else self.weight
            held[state] = max(held[state], weight)

    def read(self, word: str) -> float:
        state, best = 0, 0.0
        for letter in word:
            to = self.next[state].get(letter)
            if to is None:
                return best
            state, best = to, max(best, self.weight[to])
        return max(best, self.at_end[state])


class Since:
    """Words since one of a class, up to a most: state 0 right at it."""

    def __init__(self, bit: int, most: int) -> None:
        self.bit, self.most, self.start = bit, most, most + 1

    def step(self, state: int, kind: int) -> int:
        return 0 if kind & self.bit else min(state + 1, self.most + 1)


class Seen:
    """Whether one of a class came."""

    def __init__(self, bit: int) -> None:
        self.bit, self.start = bit, 0

    def step(self, state: int, kind: int) -> int:
        return 1 if state or kind & self.bit else 0


class Product:
    """Machines run side by side as one; its states and transitions are made on first use."""

    def __init__(self, *machines) -> None:
        self.machines = machines
        self.states = [tuple(m.start for m in machines)]
        self.number = {self.states[0]: 0}
        self.steps: dict[tuple[int, int], int] = {}

    def step(self, state: int, kind: int) -> int:
        to = self.steps.get((state, kind))
        if to is None:
            key = tuple(m.step(s, kind) for m, s in zip(self.machines, self.states[state], strict=True))
            to = self.number.get(key)
            if to is None:
                to = self.number[key] = len(self.states)
                self.states.append(key)
            self.steps[state, kind] = to
        return to

    def run(self, kinds: list[int]) -> list[int]:
        """The states before each word and after the last."""
        out, state = [0], 0
        for kind in kinds:
            state = self.step(state, kind)
            out.append(state)
        return out


@dataclass
class Grammar:
    """Weights of stems (word prefixes; a stem ending in $ is a whole word) and the curve."""

    stems: dict[str, float]
    coef: tuple[float, ...] = (-3.0, 1.0, 0.5)

    def __post_init__(self) -> None:
        self.insults = Stems(self.stems)
        self.left = Product(Since(TARGET, NEAR_TARGET), Since(NEGATION, NEAR_NEGATION), Seen(REPORT))
        self.right = Product(Since(TARGET, NEAR_TARGET))
        self.known: dict[str, tuple[int, float]] = {}
        short = [w for s in self.stems for w in (s.rstrip("$"),) if len(w) < 4]
        self.heads = {s.rstrip("$")[:4] for s in self.stems} | {w[:4] for w in THREATS} | {w + c for w in short for c in ".,;:!?\"')"}

    def read(self, word: str) -> tuple[int, float]:
        """(class, insult weight) of a lower-case word."""
        got = self.known.get(word)
        if got is None:
            if len(self.known) > 500_000:
                self.known = {}
            kind = (word in TARGETS) * TARGET | (word in NEGATIONS) * NEGATION | (word in REPORTS) * REPORT | (word in THREATS) * THREAT
            got = self.known[word] = kind, self.insults.read(word)
        return got

    def weight(self, word: str) -> float:
        return self.read(word)[1]

    def clause(self, words: list[str]) -> float:
        """The score of one clause: its matches' weights along the product machine."""
        read = [self.read(w) for w in words]
        if not any(value or kind & THREAT for kind, value in read):
            return 0.0
        kinds = [kind for kind, _ in read]
        ahead, back, total = self.left.run(kinds), self.right.run(kinds[::-1]), 0.0
        for k, (kind, value) in enumerate(read):
            if not value and not kind & THREAT:
                continue
            # States tell of the words before this one; a target may also be the word itself.
            since, negation, reported = self.left.states[ahead[k]]
            (until,) = self.right.states[back[len(words) - 1 - k]]
            target = -1 if kind & TARGET else min(since, until)
            if kind & THREAT and target < THREAT_TARGET:
                value = max(value, 1.0)
            if target < NEAR_TARGET:
                value *= WITH_TARGET
            if negation < NEAR_NEGATION:
                value *= NEGATED
            if reported:
                value *= REPORTED
            total += value
        return total

    def features(self, text: str | None) -> tuple[float, float]:
        """(heaviest clause, at most 2; log of the sum)."""
        low = (text or "").lower()
        if not any(map(self.hot, set(low.split()))):
            return 0.0, 0.0
        scores = [self.clause(_WORD.findall(c)) for c in _CLAUSE.split(low)]
        return min(2.0, max(scores)), math.log1p(sum(scores))

    def hot(self, token: str) -> bool:
        """Whether a white-space separated token holds an insult or a threat."""
        if token[:4] not in self.heads and token[:-1].isalpha():
            return False
        return any(self.weight(w) or w in THREATS for w in _WORD.findall(token))

    def score(self, text: str | None) -> float:
        z = self.coef[0] + sum(a * b for a, b in zip(self.coef[1:], self.features(text), strict=True))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def fit(rows: list[tuple[str | None, int]], min_docs: int = 4, min_odds: float = 1.6) -> Grammar:
    """Stems and curve from (text, label) rows."""
    rows = sorted(rows, key=lambda r: (r[0] or "", r[1]))
    n = Counter(y for _, y in rows)
    if not n[1] or not n[0]:
        p = (n[1] + 0.5) / (n[0] + n[1] + 1) if rows else 0.05
        return Grammar(dict.fromkeys((f"{s}$" for s in SEEDS), 1.0), (math.log(p / (1 - p)), 0.0, 0.0))
    seen: dict[int, Counter] = {0: Counter(), 1: Counter()}
    for text, y in rows:
        found = set()
        for w in set(_WORD.findall((text or "").lower())):
            found.add(w + "$")
            found.update(w[:k] for k in range(4, min(len(w), 12) + 1))
        seen[y].update(found)

    def odds(s: str) -> float:
        return math.log((seen[1][s] + 0.5) / (n[1] + 1)) - math.log((seen[0][s] + 0.5) / (n[0] + 1))

    picked: dict[str, float] = {}
    for s in sorted((s for s, c in seen[1].items() if c >= min_docs and (seen[1][s] > 3 * math.sqrt(seen[0][s] * n[1] / n[0] + 1))), key=lambda s: (len(s.rstrip("$")), s)):
        value = odds(s)
        if value < min_odds:
            continue
        # A longer stem must say clearly more than the shorter ones that hold it.
        if all(value > picked.get(s[:k], -9) + 0.7 for k in range(4, len(s))):
            picked[s] = round(min(value, 6.0) / 3, 4)
    for s in SEEDS:
        picked.setdefault(f"{s}$", 1.0)
    grammar = Grammar(picked)
    x = np.array([(1.0, *grammar.features(t)) for t, _ in rows])
    y = np.array([float(v) for _, v in rows])
    coef = np.zeros(x.shape[1])
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(x @ coef, -30, 30)))
        hess = x.T @ (x * (p * (1 - p))[:, None]) + 1e-2 * np.eye(len(coef))
        coef += np.clip(np.linalg.solve(hess, x.T @ (y - p) - 1e-2 * coef), -2, 2)
    grammar.coef = tuple(float(round(c, 6)) for c in coef)
    return grammar


def training_rows(docs: DataFrame, labels: DataFrame, max_train: int) -> list[tuple[str | None, int]]:
    """At most ``max_train`` labelled rows that are not held out."""
    picked = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    picked = cut(picked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_train))
    rows = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select("text", "toxic").distinct()  # bounded by max_train
    return [(r.text, int(r.toxic)) for r in rows.orderBy(F.xxhash64("text"), "toxic").limit(max_train).collect()]


def held_out(doc_id):
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def score_toxicity(docs: DataFrame, grammar: Grammar, threshold: float = 0.7) -> DataFrame:
    """docs -> docs + score, predicted."""
    stems, coef = grammar.stems, grammar.coef

    @F.pandas_udf("double")
    def scored(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        own = Grammar(stems, coef)
        for texts in batches:
            yield texts.map(own.score, na_action=None).astype("float64")

    rows = boxed(docs, text=F.col("text")).select("row", scored("text").alias("score"))
    return unboxed(rows, score=F.col("score"), predicted=(F.col("score") >= threshold).cast("int"))


__all__ = ["Grammar", "fit", "held_out", "score_toxicity", "training_rows"]
