"""Toxicity of whole texts by a learned lexicon, matched with edits, and the context of each match.

The lexicon holds words, and stems that many words share, that are far more common in training texts labelled toxic. It
is kept as a trie; a Levenshtein automaton run along the trie (states are sets of trie node and edits, made when first
met) finds misspelled terms and gives a token up at the first character that no term can excuse. A match counts as
quoted if it stands inside quotation marks or follows a word of reporting. Each combination of term, edits and quoting
has a weight of its own: the term's, less for edits and quotes, moved by what training texts show of that combination.
A logistic model of the weights a text gathers is fitted across halves of a bounded sample of labelled rows: a half's
texts meet the terms and weights that the other half taught, so chance finds earn no trust.

Edge cases: a null or empty text has no match and gets the base score; very long texts are read whole; a null doc_id is
scored and never learned from; several labels of one id count as toxic if one does; equal texts are learned from once;
without labels the lexicon is empty and every score is 0; an empty table gives no rows; extra columns are ignored.
"""

import ast
import math
import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_sample, held_out, id_in, id_out

#: Labelled rows to learn from, drawn by a hash of doc_id.
SAMPLE = 20_000
#: A term: toxic texts that hold it at least; its share of a text's tokens in toxic texts against others; standard errors by which more toxic texts hold it.
SUPPORT, RATIO, SURE = 4, 8, 3.2
#: Letters of a stem; in the lexicon a stem ends in this mark.
STEMS, MARK = range(4, 9), "*"
#: What an edit and a quotation leave of a term's weight where no training text tells.
EDITED, QUOTED = 0.7, 0.4
CUTOFF = 0.3
#: Tokens before a match that are searched for reporting words and opening quotes.
WINDOW = 8
#: Words that introduce another's words, in the four languages of the tables.
REPORTING = frozenset("said says called calling quote quoted quoting word words wrote meaning term sagte nannte zitat wort dit disait mot citation dijo dice palabra cita".split())
QUOTES = "\"'“”„«»‘’`"
_EDGE = re.compile(r"^[\W_]+|[\W_]+$")
_MARKS = re.compile(r"[^\w\s]+|_")
FEATURES = 5


def edits_for(term: str) -> int:
    """Edits that a word excuses; a stem, being open at its end, excuses none."""
    return 0 if len(term) < 4 or term.endswith(MARK) else 1 if len(term) < 9 else 2


class Automaton:
    """Deterministic automaton of all terms within their edits, made lazily: one step per character of a token."""

    def __init__(self, weights: dict[str, float]):
        self.weights = weights
        self.child: list[dict[str, int]] = [{}]
        self.term: list[str | None] = [None]
        self.stem: list[str | None] = [None]
        self.room: list[int] = [0]  # most edits that a term below the node allows
        self.next: list[int] = [0]
        for term in sorted(weights):
            node = 0
            self.room[0] = max(self.room[0], edits_for(term))
            for ch in term.removesuffix(MARK):
                if ch not in self.child[node]:
                    self.child[node][ch] = len(self.child)
                    self.child.append({})
                    self.term.append(None)
                    self.stem.append(None)
                    self.room.append(0)
                node = self.child[node][ch]
                self.room[node] = max(self.room[node], edits_for(term))
            (self.stem if term.endswith(MARK) else self.term)[node] = term
        self.states: dict[frozenset, int] = {}
        self.sets: list[dict[int, int]] = []
        self.moves: list[dict[str, int]] = []
        self.opens: list[str | None] = []  # the stem that a token has met in the state
        self.start = self._state({0: 0})

    def _state(self, nodes: dict[int, int]) -> int:
        """Adds nodes reached by skipping a term's character; -1 if nothing is left."""
        todo = list(nodes.items())
        best: dict[int, int] = {}
        while todo:
            node, used = todo.pop()
            if used > self.room[node] or best.get(node, 99) <= used:
                continue
            best[node] = used
            todo += [(c, used + 1) for c in self.child[node].values()]
        if not best:
            return -1
        key = frozenset(best.items())
        if key not in self.states:
            self.states[key] = len(self.sets)
            self.sets.append(best)
            self.moves.append({})
            self.opens.append(next((self.stem[n] for n, used in best.items() if used == 0 and self.stem[n]), None))
        return self.states[key]

    def _move(self, state: int, ch: str) -> int:
        out: dict[int, int] = {}
        for node, used in self.sets[state].items():
            for c, child in self.child[node].items():
                cost = used + (c != ch)
                out[child] = min(out.get(child, 99), cost)
            out[node] = min(out.get(node, 99), used + 1)
        target = self.moves[state][ch] = self._state(out)
        return target

    def match(self, token: str) -> tuple[str, int] | None:
        """The nearest term of a token within its edits, words before stems; of stems the longest."""
        state, moves, stem = self.start, self.moves, None
        for ch in token:
            step = moves[state].get(ch)
            state = self._move(state, ch) if step is None else step
            if state < 0:
                return stem and (stem, 0)
            stem = self.opens[state] or stem
        found = [(used, -self.weights[t], t) for n, used in self.sets[state].items() if (t := self.term[n]) and used <= edits_for(t)]
        if stem:
            found = [x for x in found if x[0] == 0] or [(0, 0.0, stem)]
        if not found:
            return None
        used, _, term = min(found)
        return term, used


def prior(weight: float, edits: int, quoted: bool) -> float:
    """Weight of a match that training texts tell nothing of."""
    return weight * EDITED**edits * (QUOTED if quoted else 1.0)


@dataclass
class ToxicityModel:
    #: Weights of terms, and of those (term, edits, quoted) that training texts tell of.
    weights: dict[str, float]
    #: Logistic weights: constant, then one a feature.
    beta: list[float]
    told: dict[tuple[str, int, bool], float] = field(default_factory=dict)
    _auto: Automaton | None = None
    _known: dict = field(default_factory=dict)

    def __getstate__(self):
        return self.__dict__ | {"_auto": None, "_known": {}}

    def token(self, chunk: str) -> tuple[str, int] | None:
        """(term, edits) of a white-space separated chunk."""
        bare = _EDGE.sub("", chunk).lower()
        if not bare:
            return None
        if self._auto is None:
            self._auto = Automaton(self.weights)
        return self._auto.match(bare)

    def matches(self, text) -> list[tuple[int, str, int, bool]]:
        """(position, term, edits, quoted) of each match."""
        if not isinstance(text, str) or not self.weights:
            return []
        chunks = text.split()
        known = self._known
        if len(known) > 300_000:
            known.clear()
        hits = []
        for i, hit in enumerate(map(known.get, chunks, _MISSING)):
            if hit is _NEW:
                hit = known[chunks[i]] = self.token(chunks[i])
            if hit is not None:
                hits.append((i, *hit, self._quoted(chunks, i)))
        return hits

    def weight(self, term: str, edits: int, quoted: bool) -> float:
        told = self.told.get((term, edits, quoted))
        return told if told is not None else prior(self.weights.get(term, 0.0), edits, quoted)

    @staticmethod
    def _quoted(chunks: list[str], at: int) -> bool:
        own = chunks[at]
        before = chunks[max(0, at - WINDOW) : at]
        if own[0] in QUOTES and own.rstrip(".,;:!?")[-1:] in QUOTES:
            return True
        opened = sum(c[0] in QUOTES for c in [*before, own]) > sum(c.rstrip(".,;:!?")[-1:] in QUOTES for c in before)
        closes = any(c.rstrip(".,;:!?")[-1:] in QUOTES for c in chunks[at : at + WINDOW])
        return (opened and closes) or any(_EDGE.sub("", c).lower() in REPORTING for c in before[-3:])

    def kinds(self, text) -> tuple[int, list[tuple[str, int, bool, int]]]:
        """(tokens, (term, edits, quoted, times) of the matches); no tokens are told of a text without a match."""
        found = Counter(m[1:] for m in self.matches(text))
        return len(text.split()) if found else 0, sorted((*k, n) for k, n in found.items())

    def features(self, tokens: int, kinds) -> tuple[float, ...]:
        """Plain and quoted weight of a text, each as a sum over kinds and by the share of its tokens, and the heaviest match."""
        sums, shares, most = [0.0, 0.0], [0.0, 0.0], 0.0
        for term, edits, quoted, times in kinds:
            gain = self.weight(term, edits, quoted)
            sums[quoted] += gain
            shares[quoted] += gain * times
            most = max(most, gain)
        return *map(math.log1p, sums), *(math.log1p(100 * x / max(1, tokens)) for x in shares), most

    def score(self, text) -> float:
        z = self.beta[0] + sum(b * x for b, x in zip(self.beta[1:], self.features(*self.kinds(text)), strict=True))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


_NEW = object()


class _Endless:
    def __iter__(self):
        while True:
            yield _NEW


_MISSING = _Endless()


def logistic(x: np.ndarray, y: np.ndarray, times: np.ndarray, ridge: float = 0.05, rounds: int = 60) -> list[float]:
    """Weighted logistic regression; columns whose weight would be below 0 are left out, as no match speaks for a text."""
    used = list(range(x.shape[1]))
    while True:
        z = np.column_stack([np.ones(len(x)), x[:, used]])
        beta = np.zeros(z.shape[1])
        for _ in range(rounds):
            p = 1 / (1 + np.exp(-np.clip(z @ beta, -30, 30)))
            h = (z * (times * p * (1 - p))[:, None]).T @ z + ridge * np.eye(z.shape[1])
            step = np.linalg.solve(h, z.T @ (times * (p - y)) + ridge * beta)
            beta -= step
            if np.abs(step).max() < 1e-8:
                break
        low = int(beta[1:].argmin()) if used else 0
        if not used or beta[1 + low] >= 0:
            out = [0.0] * (x.shape[1] + 1)
            out[0] = float(beta[0])
            for i, b in zip(used, beta[1:], strict=True):
                out[i + 1] = float(b)
            return out
        used.pop(low)


def labelled(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE) -> DataFrame:
    """(text, toxic, half) of a bounded sample of labelled rows that are not held out, equal texts once."""
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    some = bounded_sample(known, F.col("doc_id"), bound, 29)
    rows = docs.select("doc_id", "text").join(F.broadcast(some), "doc_id")  # bounded by the sample
    return rows.where("text is not null").groupBy("text").agg((F.max("toxic") > 0).cast("int").alias("toxic")).withColumn("half", F.pmod(F.xxhash64("text", F.lit(31)), F.lit(2)).cast("int"))


def terms_of(text: str) -> dict[str, int]:
    """Words and stems of a text with their numbers."""
    out: dict[str, int] = {}
    for word, n in Counter(_MARKS.sub(" ", text.lower()).split()).items():
        if 3 <= len(word) <= 40:
            out[word] = n
        for size in STEMS:
            if size > len(word):
                break
            stem = word[:size] + MARK
            out[stem] = out.get(stem, 0) + n
    return out


def candidates(rows: DataFrame) -> list[tuple[str, dict[tuple[int, int], tuple[int, float]]]]:
    """(term, (texts, sum of its shares of their tokens) by (half, toxic)) of words and stems that may pass the tests."""
    cells = [(h, t) for h in (0, 1) for t in (0, 1)]

    def task(frames):
        import pandas as pd

        def part(sums):
            return pd.DataFrame([(k, *v) for k, v in sums.items()], columns=["term", *[f"{c}{h}{t}" for h, t in cells for c in "nd"]])

        sums: dict[str, list] = {}
        for f in frames:
            for text, half, toxic in zip(f["text"], f["half"], f["toxic"], strict=True):
                found, at = terms_of(text), 2 * cells.index((half, toxic))
                tokens = max(1, len(text.split()))
                for term, n in found.items():
                    own = sums.setdefault(term, [0, 0.0] * 4)
                    own[at] += 1
                    own[at + 1] += n / tokens
            if len(sums) > 400_000:
                yield part(sums)
                sums = {}
        yield part(sums)

    made = rows.mapInPandas(task, "term string, " + ", ".join(f"n{h}{t} long, d{h}{t} double" for h, t in cells))
    seen = made.groupBy("term").agg(*[F.sum(f"{c}{h}{t}").alias(f"{c}{h}{t}") for h, t in cells for c in "nd"])
    enough = F.col("n01") + F.col("n11") >= SUPPORT
    # their number is bounded by the sample; the tests themselves follow on the driver
    found = seen.where(enough & (F.col("d01") + F.col("d11") > F.col("d00") + F.col("d10"))).collect()
    return sorted((r["term"], {c: (r["n%d%d" % c], r["d%d%d" % c]) for c in cells}) for r in found)


def lexicon(found, texts: dict[tuple[int, int], int], halves=(0, 1)) -> dict[str, float]:
    """Weights of the terms beyond chance in the given halves: the smoothed log ratio of their shares of a text.

    The support is a count, not a share of all toxic texts: a rare language or a much inflected word needs no more
    texts of its own when other languages have many. Of terms that begin alike, the surest stands for the others.
    """
    toxic, rest = (sum(texts.get((h, t), 0) for h in halves) for t in (1, 0))
    ranked = []
    for term, cells in found:
        (good, thin), (bad, dense) = ([sum(cells[h, t][i] for h in halves) for i in (0, 1)] for t in (0, 1))
        if bad < SUPPORT:
            continue
        gap = math.log((bad + 0.5) / (toxic + 1)) - math.log((good + 0.5) / (rest + 1))
        sure = gap / math.sqrt(1 / (bad + 0.5) + 1 / (good + 0.5))
        one = dense / bad  # a text's worth
        weight = math.log((dense + one / 2) / (toxic + 1)) - math.log((thin + one / 2) / (rest + 1))
        if sure >= SURE and weight >= math.log(RATIO):
            ranked.append((-sure, term.endswith(MARK), -len(term), term, weight, bad))
    out: dict[str, float] = {}
    under: dict[str, int] = {}  # toxic texts of the chosen terms that begin so
    for _, is_stem, _, term, weight, bad in sorted(ranked):
        bare = term.removesuffix(MARK)
        if any(bare[:n] + MARK in out for n in STEMS if n <= len(bare)) or (is_stem and 2 * under.get(bare, 0) >= bad):
            continue
        out[term] = weight
        for n in STEMS:
            if n <= len(bare):
                under[bare[:n]] = under.get(bare[:n], 0) + bad
    return out


def evidence(weights: dict[str, float], seen: list[tuple[int, int, list, int]]) -> dict[tuple[str, int, bool], float]:
    """Weights of (term, edits, quoted) from (toxic, tokens, kinds, texts), by their shares of a text's tokens.

    A text's worth of the prior weight stands against what was seen; no weight is below 0.
    """
    texts = [0, 0]
    shares: dict[tuple, list[float]] = {}
    held: dict[tuple, int] = {}
    for toxic, tokens, kinds, n in seen:
        texts[toxic] += n
        for *kind, times in kinds:
            if weights.get(kind[0]):
                key = tuple(kind)
                shares.setdefault(key, [0.0, 0.0])[toxic] += n * times / tokens
                held[key] = held.get(key, 0) + n
    out = {}
    for key, (good, bad) in shares.items():
        one = (good + bad) / held[key] / max(1, sum(texts))
        out[key] = max(0.0, math.log((bad / max(1, texts[1]) + one * math.exp(prior(weights[key[0]], *key[1:]))) / (good / max(1, texts[0]) + one)))
    return out


def train(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE) -> ToxicityModel:
    rows = labelled(docs, labels, bound)
    texts = {(r["half"], r["toxic"]): r["count"] for r in rows.groupBy("half", "toxic").count().collect()}
    if {t for _, t in texts} != {0, 1}:
        return ToxicityModel({}, [-30.0] + [0.0] * FEATURES)
    found = candidates(rows)
    whole, *by_half = (lexicon(found, texts, h) for h in ((0, 1), (0,), (1,)))
    shared = rows.sparkSession.sparkContext.broadcast(ToxicityModel({**by_half[0], **by_half[1], **whole}, []))

    def task(frames):
        import pandas as pd

        for f in frames:
            yield pd.DataFrame({"half": f["half"], "toxic": f["toxic"], "kinds": [repr(shared.value.kinds(t)) for t in f["text"]]})

    # a row per distinct list of matches of the sample; most texts have none
    got = rows.mapInPandas(task, "half int, toxic int, kinds string").groupBy("half", "toxic", "kinds").count().collect()
    seen = sorted((r["half"], r["toxic"], *ast.literal_eval(r["kinds"]), r["count"]) for r in got)
    x, y, times = [], [], []
    for h in (0, 1):
        other = ToxicityModel(by_half[1 - h], [], evidence(by_half[1 - h], [s[1:] for s in seen if s[0] != h]))
        for _, toxic, tokens, kinds, n in (s for s in seen if s[0] == h):
            x.append(other.features(tokens, kinds))
            y.append(float(toxic))
            times.append(float(n))
    return ToxicityModel(whole, logistic(np.array(x), np.array(y), np.array(times)), evidence(whole, [s[1:] for s in seen]))


def score(docs: DataFrame, model: ToxicityModel, cutoff: float = CUTOFF) -> DataFrame:
    """(doc_id, held_out, score, predicted, matches) per document."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def task(frames):
        for f in frames:
            found = [shared.value.score(t) for t in f["text"]]
            f = f.drop(columns="text")
            f["score"] = found
            yield f

    scored = docs.select(id_in("doc_id"), held_out(F.col("doc_id")).alias("held_out"), "text").mapInPandas(task, "doc_id long, held_out boolean, score double")
    return id_out(scored, "doc_id").withColumn("predicted", (F.col("score") >= cutoff).cast("int"))
