"""Language identification: sparse multinomial logistic regression on TF-IDF of character n-grams.

Texts are lower-cased; n-grams of one to three characters are hashed into 2^16 features. Document
frequencies are counted over all learning documents. Weights are trained with follow-the-regularised-
leader steps under an elastic net (L1 leaves most of them zero) on a sample of at most `per_language`
documents of each language in expectation and never over twice that for all, and a temperature is then
fitted on a fifth of the sample that the weights have not seen.

Languages are the `languages` most frequent values of lang among the learning rows.

Defined results: a null text or one without letters is `und` with score 0; very long texts are read whole; bytes that
are no UTF-8 are read as replacement characters; rows whose lang is null are not learned from; null ids belong to fold 0; repeated rows
are learned from as they come and predicted alike; without any learning row every text is `und`; an empty table gives
an empty result; columns `lang_pred` and `lang_score` of the input are replaced.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_column, fold, map_rows

FEATURES = 1 << 16
PER_LANGUAGE = 1_000
LANGUAGES = 400
_PRIME = np.uint32(2654435761)


def ngram_ids(text: str) -> np.ndarray:
    """Feature number of every n-gram (n = 1, 2, 3) of the text, repeats included."""
    c = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    one = c * _PRIME
    two = (one[:-1] ^ (one[1:] >> np.uint32(11))) * _PRIME + np.uint32(7)
    three = (two[:-1] ^ (one[2:] >> np.uint32(9))) * _PRIME + np.uint32(77)
    return np.concatenate([x >> np.uint32(16) for x in (one, two, three)]) if len(c) else one


def tf_idf(text: str, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    counts = np.bincount(ngram_ids(text), minlength=FEATURES)
    feats = np.flatnonzero(counts)
    x = (1 + np.log(counts[feats])) * idf[feats]
    return feats, x / max(1e-12, float(np.sqrt(x @ x)))


def has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


class Regression:
    """Multinomial logistic regression, follow-the-regularised-leader with L1 and L2 penalties."""

    def __init__(self, labels: list[str], idf: np.ndarray, alpha=0.5, beta=1.0, l1=0.02, l2=0.02) -> None:
        self.labels, self.idf, self.temperature = labels, idf, 1.0
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z = np.zeros((FEATURES, len(labels)))
        self.n = np.zeros((FEATURES, len(labels)))
        self.w = None

    def weights(self, feats) -> np.ndarray:
        z, n = self.z[feats], self.n[feats]
        shrunk = np.sign(z) * np.maximum(np.abs(z) - self.l1, 0)
        return -shrunk / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)

    def step(self, feats, x, y: int) -> None:
        w = self.weights(feats)
        p = softmax(x @ w)
        p[y] -= 1
        g = x[:, None] * p[None, :]
        sigma = (np.sqrt(self.n[feats] + g * g) - np.sqrt(self.n[feats])) / self.alpha
        self.z[feats] += g - sigma * w
        self.n[feats] += g * g

    def fit(self, rows: list[tuple[str, int]], epochs: int = 3, seed: int = 5) -> Regression:
        rng = np.random.default_rng(seed)
        order = rng.permutation(len(rows))
        cut = len(rows) - len(rows) // 5
        learn, check = order[:cut], order[cut:]
        data = [tf_idf(t, self.idf) for t, _ in rows]
        for _ in range(epochs):
            for i in rng.permutation(learn):
                self.step(*data[i], rows[i][1])
        self.w = self.weights(slice(None)).astype(np.float32)
        self.z = self.n = None
        if len(check):
            logits = np.stack([data[i][1] @ self.w[data[i][0]] for i in check])
            y = np.array([rows[i][1] for i in check])
            grid = np.exp(np.linspace(np.log(0.02), np.log(20), 80))
            self.temperature = float(min(grid, key=lambda t: _nll(logits / t, y)))
        return self

    def predict(self, text: str | None) -> tuple[str, float]:
        if not has_letter(text):
            return "und", 0.0
        feats, x = tf_idf(text, self.idf)
        p = softmax((x @ self.w[feats]) / self.temperature)
        k = int(p.argmax())
        return self.labels[k], float(p[k])


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max())
    return e / e.sum()


def _nll(logits, y) -> float:
    top = logits.max(axis=1)
    return float((np.log(np.exp(logits - top[:, None]).sum(axis=1)) + top - logits[np.arange(len(y)), y]).mean())


def document_frequencies(docs: DataFrame) -> np.ndarray:
    """Number of texts, and in how many each feature occurs; each task sends one row a feature at most."""

    def count(batches):
        total = np.zeros(FEATURES + 1, np.int64)
        mark = np.zeros(FEATURES, bool)
        for b in batches:
            for text in b.column(0).to_pylist():
                mark[:] = False
                mark[ngram_ids(text or "")] = True
                total[:-1] += mark
                total[-1] += 1
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], ["f", "n"])

    rows = docs.select("text").mapInArrow(count, "f int, n long").groupBy("f").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(FEATURES + 1, np.int64)
    out[rows["f"].to_numpy()] = rows["n"].to_numpy()
    return out


def fit(docs: DataFrame, mod: int = 4, keep_out: int = 2, per_language: int = PER_LANGUAGE, languages: int = LANGUAGES) -> Regression | None:
    learn = docs.where((fold("doc_id", mod) != keep_out) & F.col("lang").isNotNull()).select("doc_id", "text", "lang")
    sizes = {r["lang"]: r["count"] for r in learn.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(languages).collect()}
    if not sizes:
        return None
    learn = learn.where(F.col("lang").isin(list(sizes)))
    df = document_frequencies(learn)
    idf = np.log((1 + df[-1]) / (1 + df[:-1])) + 1
    share = F.create_map(*[x for k, v in sorted(sizes.items()) for x in (F.lit(k), F.lit(min(1.0, per_language / v)))])
    chance = F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 40)) / F.lit(float(1 << 40))
    sample = learn.where(F.col("text").isNotNull() & (chance < share[F.col("lang")])).select("text", "lang")
    rows = sorted({(r["text"], r["lang"]) for r in sample.limit(2 * per_language * len(sizes)).collect()}, key=lambda r: (r[1], r[0]))
    labels = sorted({lang for _, lang in rows})
    return Regression(labels, idf).fit([(t, labels.index(lang)) for t, lang in rows]) if rows else None


def predict(docs: DataFrame, model: Regression | None) -> DataFrame:
    """docs (any columns, one named text) plus lang_pred and lang_score."""
    docs = docs.drop("lang_pred", "lang_score")  # own names win
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def one(batch):
        m = shared.value
        texts = (None if x is None else x.decode("utf-8", "replace") for x in byte_column(batch, "text"))
        found = [m.predict(x) if m else ("und", 0.0) for x in texts]
        cols = [*batch.columns, pa.array([x for x, _ in found], pa.string()), pa.array([x for _, x in found], pa.float64())]
        yield pa.RecordBatch.from_arrays(cols, [*batch.schema.names, "lang_pred", "lang_score"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return map_rows(docs, f"{schema}, lang_pred string, lang_score double", one)


def language_report(docs: DataFrame) -> DataFrame:
    """The contract's columns for every document."""
    return predict(docs.select("doc_id", "text"), fit(docs)).select(
        "doc_id", (fold("doc_id", 4) == 2).alias("held_out"), "lang_pred", F.col("lang_score").alias("score")
    )
