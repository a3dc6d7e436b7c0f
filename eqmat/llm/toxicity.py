"""Toxicity by a learned lexicon: Levenshtein automata run together with a trie of the terms catch misspelled words,
and a window of context around each hit tells quotation from abuse.

The product of trie and automaton is made deterministic as it is used: a state is the set of (trie node, edits so
far) that the characters read leave open, and a word is looked up by following one transition for each character
until the set is empty, whatever the number of terms.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_WORD = re.compile(r"[^\W_]+(?:[@$!*][^\W_]+)*")
#: Words that report speech, and marks that open or close a quotation.
REPORTING = frozenset("said says wrote writes called calls quote quoted quotes term word phrase insult insults comment posted reported dijo escribió sagte schrieb dit écrit".split())
QUOTES = frozenset("\"“”„«»‹›")
STEMS = range(4, 9)  # lengths of stems that are learned
BEGUN = 3  # what a word gets that is near no whole term and goes on after a stem
SPAN = 60  # characters of context on either side of a hit


def allowed_edits(term: str) -> int:
    return 0 if len(term) < 5 else 1 if len(term) < 8 else 2


class LexiconAutomaton:
    """Finds the least number of edits between a word and any term, within the edits that the term allows."""

    def __init__(self, terms: list[str]):
        """A term with * at its end is a stem: it takes no edits, and any word that goes on after it is begun by it."""
        self.child: list[dict[str, int]] = [{}]
        self.ends: list[int] = [-1]  # edits allowed by the term that ends here; -1: none ends here
        self.most: list[int] = [0]  # largest number of edits allowed by any term at or below
        self.stems: set[int] = set()
        for term in terms:
            stem = term.endswith("*")
            term = term.removesuffix("*")
            k, node = 0 if stem else allowed_edits(term), 0
            self.most[0] = max(self.most[0], k)
            for c in term:
                if c not in self.child[node]:
                    self.child[node][c] = len(self.child)
                    self.child.append({})
                    self.ends.append(-1)
                    self.most.append(0)
                node = self.child[node][c]
                self.most[node] = max(self.most[node], k)
            if stem:
                self.stems.add(node)
            else:
                self.ends[node] = max(self.ends[node], k)
        self.alphabet = frozenset(c for d in self.child for c in d)
        self.ids: dict[frozenset, int] = {frozenset(): 0}
        self.sets: list[frozenset] = [frozenset()]
        self.steps: list[dict[str, int]] = [{}]
        self.accept: list[int] = [-1]
        self.done: list[bool] = [False]
        self.start = self._state({0: 0}) if terms else 0

    def _state(self, open_: dict[int, int]) -> int:
        """The state that holds these (node, edits), closed under leaving out characters of the term."""
        todo = list(open_)
        while todo:
            node = todo.pop()
            e = open_[node] + 1
            for below in self.child[node].values():
                if e <= self.most[below] and e < open_.get(below, 99):
                    open_[below] = e
                    todo.append(below)
        key = frozenset(open_.items())
        if key not in self.ids:
            self.ids[key] = len(self.sets)
            self.sets.append(key)
            self.steps.append({})
            self.accept.append(min((e for n, e in key if e <= self.ends[n]), default=-1))
            self.done.append(any(e == 0 and n in self.stems for n, e in key))
        return self.ids[key]

    def _step(self, state: int, c: str) -> int:
        after: dict[int, int] = {}
        for node, e in self.sets[state]:
            moves = [(below, e + (x != c)) for x, below in self.child[node].items()]  # same character, or one for another
            moves.append((node, e + 1))  # a character too many
            for to, cost in moves:
                if cost <= self.most[to] and cost < after.get(to, 99):
                    after[to] = cost
        return self._state(after)

    def edits(self, word: str) -> int:
        """BEGUN if no whole term is near enough but a stem begins the word, -1 if neither."""
        state, steps, alphabet, done, other = self.start, self.steps, self.alphabet, self.done, -1
        for c in word:
            if done[state]:
                other = BEGUN
            if c not in alphabet:
                c = ""
            to = steps[state].get(c)
            if to is None:
                to = steps[state][c] = self._step(state, c)
            if not to:
                return other
            state = to
        return self.accept[state] if self.accept[state] >= 0 else other


class ToxicityModel:
    """Lexicon, words that only look like a term, and the weights of a logistic regression on counts of hits.

    A single word that a stem begins tells nothing, as chance brings one into a long text; the ones after it count."""

    FEATURES = ("exact", "one_edit", "two_edits", "begun", "quoted")
    PRIOR = (4.0, 1.5, 0.5, 4.0, 0.2)

    def __init__(self, terms: list[str], harmless: set[str] | frozenset[str] = frozenset(), weights: np.ndarray | None = None, bias: float = -3.0):
        self.terms, self.harmless = sorted(terms), frozenset(harmless)
        self.weights = np.array(self.PRIOR) if weights is None else weights
        self.bias, self.auto = bias, LexiconAutomaton(self.terms)

    def __reduce__(self):
        return ToxicityModel, (self.terms, self.harmless, self.weights, self.bias)

    def word_edits(self, words) -> dict[str, int]:
        """Those of the words that are near a term, with their edits."""
        find = self.auto.edits
        return {w: e for w in words if (e := find(w)) >= 0 and w not in self.harmless}

    @staticmethod
    def quoted(text: str, start: int, end: int) -> bool:
        """Whether a hit is reported rather than meant: a quotation mark on both sides, or a reporting word, within
        SPAN characters."""
        before, after = text[max(0, start - SPAN) : start], text[end : end + SPAN]
        if any(c in QUOTES for c in before.rpartition("\n")[2]) and any(c in QUOTES for c in after.partition("\n")[0]):
            return True
        return not REPORTING.isdisjoint(before.split()[-6:]) or not REPORTING.isdisjoint(after.split()[:6])

    def counts(self, texts: list[str | None]) -> np.ndarray:
        """Hits of each kind for each text."""
        low = [(t or "").lower() for t in texts]
        words = [_WORD.findall(t) for t in low]
        hits = self.word_edits(set().union(*words)) if words else {}
        out = np.zeros((len(texts), len(self.FEATURES)))
        if hits:
            for k, own in enumerate(words):
                found = [w for w in own if w in hits]
                if found:
                    wanted = set(found)
                    for m in _WORD.finditer(low[k]):
                        if (w := m.group()) in wanted:
                            out[k, 4 if self.quoted(low[k], m.start(), m.end()) else hits[w]] += 1
        return out

    @staticmethod
    def features(counts: np.ndarray) -> np.ndarray:
        x = counts.copy()
        x[:, BEGUN] = np.maximum(x[:, BEGUN] - 1, 0)
        return np.log1p(x)

    def judge(self, counts: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.features(counts) @ self.weights + self.bias, -30, 30)))

    def scores(self, texts: list[str | None]) -> np.ndarray:
        return self.judge(self.counts(texts))

    @classmethod
    def fit(cls, texts: list[str], toxic: list[int], least_lift: float = 20.0, least_texts: int = 3, chance: float = 1e-5) -> ToxicityModel:
        """Terms are words that stand in far more toxic than clean texts, and beginnings of words that come more than once
        in far more of them; equal texts count once. Whole words need texts enough that chance would not make them all
        toxic; a stem, which pools the forms of a word where no form is frequent, needs ``least_texts`` toxic ones, and
        its occurrences, of which at most three a text count, must lean to toxic texts beyond ``chance``."""
        pairs = sorted(dict(zip(texts, toxic, strict=True)).items())
        n = Counter(y for _, y in pairs)
        if not n[1] or not n[0]:
            return cls([], bias=-3.0 if not n[1] else 3.0)
        df, twice, shown, length = {0: Counter(), 1: Counter()}, {0: Counter(), 1: Counter()}, {0: Counter(), 1: Counter()}, Counter()
        for t, y in pairs:
            words = _WORD.findall(t.lower())
            length[y] += len(words)
            df[y].update({w for w in words if len(w) >= 4})
            for stem, k in Counter(w[:j] for w in words for j in STEMS if len(w) > j).items():
                shown[y][stem] += min(k, 3)
                twice[y][stem] += k > 1
        # A word that says nothing of toxicity stands in k toxic texts and no clean one with a chance of share ** k.
        share = n[1] / (n[0] + n[1])
        least = max(5, math.ceil(math.log(1e-4) / math.log(share)))

        def telling(counts: dict[int, Counter], floor: int) -> list[str]:
            found = (w for w, k in counts[1].items() if k >= floor and (k / n[1]) / ((counts[0][w] + 0.5) / n[0]) >= least_lift)
            return sorted(found, key=lambda w: (-counts[1][w], w))

        def by_chance(k: int, of: int, p: float) -> float:
            return sum(math.exp(math.lgamma(of + 1) - math.lgamma(i + 1) - math.lgamma(of - i + 1) + i * math.log(p) + (of - i) * math.log1p(-p)) for i in range(k, of + 1))

        whole, begun = telling(df, least), telling(twice, least_texts)
        # A stem that mostly is one word is that word; one that only lengthens another stem adds nothing.
        begun = [s for s in begun if max((df[1][w] for w in whole if w.startswith(s)), default=0) < 0.5 * twice[1][s]]
        worded = length[1] / (length[0] + length[1])
        begun = [s for s in begun if by_chance(shown[1][s], shown[0][s] + shown[1][s], worded) < chance]
        begun = [s for s in begun if not any(s != t and s.startswith(t) for t in begun)]
        model = cls(whole + [s + "*" for s in begun])
        near = {w for w, e in model.word_edits(df[0]).items() if 0 < e < BEGUN}
        model.harmless = frozenset(w for w in near if df[0][w] / n[0] >= df[1][w] / n[1])
        x, y = model.features(model.counts([t for t, _ in pairs])), np.array([y for _, y in pairs], float)
        prior = np.array(cls.PRIOR)
        w, b = prior.copy(), math.log(n[1] / n[0])
        for _ in range(600):  # gradient descent, held near the prior so that what the sample lacks stays sensible
            p = 1 / (1 + np.exp(-np.clip(x @ w + b, -30, 30)))
            w -= 0.5 * (x.T @ (p - y) / len(y) + 0.002 * (w - prior))
            b -= 0.5 * float(np.mean(p - y))
        model.weights, model.bias = np.maximum(w, 0), b
        return model


def train(docs: DataFrame, labels: DataFrame, per_label: int = 1500) -> ToxicityModel:
    """Fit on about ``per_label`` documents of each label, picked by a hash of doc_id: a bounded sample.

    docs(doc_id, text), labels(doc_id, toxic); rows with a null id, text or label teach nothing, any toxic above 0 is
    1, of several labels for one document the highest counts, of several texts the least.
    The picked ids, about ``per_label`` for each of two labels whatever the size of the input, are broadcast, so that
    docs are read once and only the picked texts move."""
    from eqmat.llm.language import balanced_sample

    y = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max((F.col("toxic") > 0).cast("int")).alias("toxic"))
    picked = balanced_sample(y, "toxic", "doc_id", per_label).withColumnRenamed("doc_id", "id")
    rows = docs.where("text is not null").select("doc_id", "text").join(F.broadcast(picked), F.col("doc_id") == F.col("id"))
    rows = rows.groupBy("id", "toxic").agg(F.min("text").alias("text")).collect()
    return ToxicityModel.fit([r["text"] for r in rows], [r["toxic"] for r in rows])


def score(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """docs(doc_id, text) -> doc_id, score, n_hits (exact, misspelled or begun by a stem, outside quotations). Null and empty texts get
    the score of a text without hits; repeated rows are scored each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                found = model.counts(part.column(1).to_pylist())
                p, hits = model.judge(found), found[:, : BEGUN + 1].sum(axis=1).astype(np.int64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(p), pa.array(hits)], names=["doc_id", "score", "n_hits"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, score double, n_hits long")
