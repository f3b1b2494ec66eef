"""Language of whole texts: averaged embeddings of hashed subwords under a linear softmax, with calibrated rejection.

Subwords are byte n-grams of the lower-cased text, spaces included, so that n-grams mark word starts and ends. A text's
vector is the mean of its subwords' embeddings. Training is stochastic gradient descent in numpy on a bounded sample of
labelled rows; a temperature is fitted on a part of the sample left out of it. For prediction, embeddings and weights
fold into one table of class scores per subword.

Edge cases: a null text, or one without a letter, is `und` with score 0; very long texts are read whole; rows with a
null lang are predicted but not learned from; if nothing can be learned from, every text is `und`; an empty table gives
no rows; extra columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_sample, give_back, held_out, id_in, id_out, lean

UNKNOWN = "und"
ORDERS = (2, 3, 4)
BUCKETS, DIMENSIONS = 1 << 16, 16
#: Labelled rows to learn from: this many are drawn by a hash of doc_id.
SAMPLE = 3000
#: Share of the sample that sets the temperature and the rejection threshold.
CALIBRATION = 0.2
_LETTER = re.compile(r"[^\W\d_]")


def has_letter(text) -> bool:
    return isinstance(text, str) and _LETTER.search(text) is not None


def subwords(data: np.ndarray, buckets: int = BUCKETS):
    """Hashed n-grams of each order, one array an order, by position."""
    b = data.astype(np.uint32)
    key = np.zeros(len(b), np.uint32)
    for n in range(1, max(ORDERS) + 1):
        size = len(b) - n + 1
        if size <= 0:
            return
        key = (key[:size] * np.uint32(0x01000193)) ^ b[n - 1 : n - 1 + size]
        if n in ORDERS:
            mixed = (key + np.uint32(n)) * np.uint32(0x9E3779B1)
            yield (mixed >> np.uint32(15)) % np.uint32(buckets)


def text_bytes(text: str) -> np.ndarray:
    return np.frombuffer((" " + text.lower() + " ").encode(), np.uint8)


@dataclass
class LanguageModel:
    classes: list[str]
    table: np.ndarray  # class scores of each subword
    bias: np.ndarray
    temperature: float
    #: Lowest calibrated score that is not rejected.
    threshold: float

    def scores(self, text: str) -> np.ndarray:
        total, n = np.zeros(len(self.classes)), 0
        data = text_bytes(text)
        for a in range(0, len(data), 1 << 20):  # blocks overlap by an n-gram less a byte: memory is bounded, no n-gram is lost or read twice
            block = data[a : a + (1 << 20) + max(ORDERS) - 1]
            for order, keys in zip(ORDERS, subwords(block), strict=False):
                keys = keys[: min(len(keys), max(0, min(len(data) - order + 1 - a, 1 << 20)))]
                total += self.table.take(keys, axis=0).sum(axis=0, dtype=np.float64)
                n += len(keys)
        z = (total / max(n, 1) + self.bias) / self.temperature
        e = np.exp(z - z.max())
        return e / e.sum()

    def predict(self, text) -> tuple[str, float]:
        if not self.classes or not has_letter(text):
            return UNKNOWN, 0.0
        p = self.scores(text)
        best = int(p.argmax())
        return self.classes[best], float(p[best])


def bag(text: str) -> tuple[np.ndarray, np.ndarray]:
    """A text's subwords and their shares: 65,536 at most, however long the text."""
    keys = np.concatenate([*subwords(text_bytes(text)), np.zeros(0, np.uint32)]).astype(np.int64)
    ids, n = np.unique(keys, return_counts=True)
    return ids, (n / max(1, n.sum())).astype(np.float32)


def fit(bags: list[tuple[np.ndarray, np.ndarray]], langs: list[str], epochs: int = 12, rate: float = 0.5, seed: int = 5) -> LanguageModel:
    classes = sorted(set(langs))
    if not classes:
        return LanguageModel([], np.zeros((BUCKETS, 0), np.float32), np.zeros(0), 1.0, 0.0)
    rng = np.random.default_rng(seed)
    y = np.array([classes.index(x) for x in langs])
    order = rng.permutation(len(bags))
    cut = max(1, int(len(order) * CALIBRATION)) if len(order) > 10 else 0
    check, train = order[:cut], order[cut:]
    emb = rng.normal(0, 0.1, (BUCKETS, DIMENSIONS)).astype(np.float32)
    w = np.zeros((DIMENSIONS, len(classes)), np.float32)
    w += rng.normal(0, 0.1, w.shape).astype(np.float32)
    bias = np.zeros(len(classes), np.float32)
    for epoch in range(epochs):
        step = rate * (1 - epoch / epochs)
        for i in rng.permutation(train):
            ids, share = bags[i]
            h = share @ emb[ids]
            z = h @ w + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[y[i]] -= 1
            back = w @ p
            w -= step * np.outer(h, p)
            bias -= step * 0.1 * p
            # subwords of a text share one gradient; scaled up, as each has a small share of the mean
            emb[ids] -= (step * 20) * np.outer(np.minimum(share * 50, 1), back).astype(np.float32)
    held = check if cut else train
    z = np.array([bags[i][1] @ emb[bags[i][0]] @ w + bias for i in held], np.float64).reshape(len(held), len(classes))
    truth = y[held]

    def loss(t: float) -> float:
        s = z / t
        s -= s.max(axis=1, keepdims=True)
        return float((np.log(np.exp(s).sum(axis=1)) - s[np.arange(len(s)), truth]).mean())

    temperature = min((float(t) for t in np.geomspace(0.2, 20, 60)), key=loss)
    s = z / temperature
    p = np.exp(s - s.max(axis=1, keepdims=True))
    p /= p.sum(axis=1, keepdims=True)
    # rejection keeps nearly all texts that are right: half the score that 99.5 % of them reach
    right = p.max(axis=1)[p.argmax(axis=1) == truth]
    threshold = float(np.quantile(right, 0.005)) / 2 if len(right) else 0.0
    return LanguageModel(classes, (emb @ w).astype(np.float32), bias.astype(np.float64), temperature, min(threshold, 0.5))


def train(docs: DataFrame, bound: int = SAMPLE) -> LanguageModel:
    """Learns from text and lang of rows that are not held out; the sample is the same in every run."""
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id", "text", "lang")

    def task(frames):
        import pandas as pd

        for f in frames:
            found = [bag(t) if has_letter(t) else None for t in f["text"]]
            yield pd.DataFrame([(d, lang, b[0].astype("<u2").tobytes(), b[1].tobytes()) for d, lang, b in zip(f["doc_id"], f["lang"], found, strict=True) if b], columns=["doc_id", "lang", "ids", "shares"])

    # bags, not texts, come to the driver: each has 6 bytes a subword and BUCKETS subwords at most, and their number is bounded
    rows = bounded_sample(known, F.col("doc_id"), bound, 17).select(id_in("doc_id"), "text", "lang").mapInPandas(lean(task), "doc_id long, lang string, ids binary, shares binary").collect()
    rows = sorted(rows, key=lambda r: (r["doc_id"], bytes(r["ids"]), bytes(r["shares"]), r["lang"]))
    return fit([(np.frombuffer(r["ids"], "<u2"), np.frombuffer(r["shares"], np.float32)) for r in rows], [r["lang"] for r in rows])


def predict(docs: DataFrame, model: LanguageModel, keep: list[str] | None = None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, rejected), with the columns named in keep after them."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    keep = [c for c in keep or [] if c != "doc_id"]

    def task(frames):
        model = shared.value
        for f in frames:
            found = [model.predict(t) for t in f["_text"]]
            f = f.drop(columns="_text")
            f["lang_pred"], f["score"] = [x[0] for x in found], [x[1] for x in found]
            yield f

    cols = docs.select(id_in("doc_id"), held_out(F.col("doc_id")).alias("held_out"), F.col("text").alias("_text"), *[F.col(c).alias(f"_keep{i}") for i, c in enumerate(keep)])
    extra = "".join(f", _keep{i} {docs.schema[c].dataType.simpleString()}" for i, c in enumerate(keep))
    out = id_out(cols.mapInPandas(lean(task), f"doc_id long, held_out boolean{extra}, lang_pred string, score double"), "doc_id")
    return out.select("doc_id", "held_out", "lang_pred", "score", ((F.col("lang_pred") == UNKNOWN) | (F.col("score") < model.threshold)).alias("rejected"), *[F.col(f"_keep{i}").alias(c) for i, c in enumerate(keep)])


def keep_known(docs: DataFrame, model: LanguageModel | None = None) -> DataFrame:
    """docs without the texts that the model rejects, in docs' columns; the verdict is a column function, so rows pass through unchanged."""
    model = model or train(docs)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("boolean")
    def kept(text):
        import pandas as pd

        found = [shared.value.predict(t) for t in text]
        give_back()
        return pd.Series([lang != UNKNOWN and score >= shared.value.threshold for lang, score in found], dtype=bool)

    return docs.where(kept("text"))
