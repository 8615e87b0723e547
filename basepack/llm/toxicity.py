"""Toxicity by compression distance: one zstandard dictionary per class, and lengths of windows under both.

Learning rows fall into two folds by text hash. From the first fold:

* every word counts once for each different pair of neighbours it has, by label, so that copies of a document count
  once. Words tell if their log-likelihood ratio reaches `GAIN`, whatever the ratio of the best word: words of a rare
  language stay in;
* the toxic dictionary is trained by zstandard on telling words of toxic texts, with their spaces, as often as they
  have contexts. What its cover leaves out of so little text is put behind, so that every telling word is held;
* the ordinary dictionary is trained by zstandard on three-word windows of ordinary texts.

Both are given to the compressor as content, and the toxic one is the ordinary one with some of its content replaced
by the toxic content: lengths then differ by what the toxic content matches. (With the trained entropy tables a short
match saves no whole byte and the distances of toxic and ordinary windows overlap.) Both end in the same frame. A window is
`WINDOW` words, every `STRIDE` words, followed by that frame: zstandard stores very short inputs as they are, and
within a compressible frame every matched byte shows.

The distance of a window is its length under the ordinary dictionary less that under the toxic one. Matches have at least
`MATCH` bytes, so only a framed window with `MATCH` bytes of the toxic content can be shorter for it: the others have
distance 0 by definition and are not compressed. (What the toxic content replaces would put some of them below 0, and zstandard,
which indexes a dictionary with losses, a few of them above.) The content that the toxic one replaces ends in a space too, since otherwise every framed window would meet
one of the two ends. A text is described by its largest distances and by number and share of windows at each of several
thresholds. The second fold calibrates: a logistic regression over the description, moved so that `THRESHOLD` stands where
F1 is best.

Learning uses one text (least hash) of each of at most `max_train` labelled ids (least id hash). All texts are scored
whole, in one pass.

Defined results: null, empty and blank texts have no window and get the score of no hit; very long texts and words are
read whole; repeated rows are scored alike; ids that are null or without label are only scored; two labels of one id
count as the larger; without both classes among the learning rows every score is the share of toxic ones, or 0; without
any telling word scores are alike; an empty table gives an empty result; a column `toxic_score` of the input is replaced.
"""

from __future__ import annotations

import math
from zlib import crc32

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_column, fold, map_rows, materialise, words_of
from .quality import learning_texts

MAX_TRAIN = 12_000
#: Telling words at most, by gain.
TOXIC_WORDS = 4_000
#: Log-likelihood ratio, contexts in toxic texts and ratio of shares from which a word tells.
GAIN, CONTEXTS, RATIO = 15.0, 4, 4.0
ORDINARY_BYTES = 1 << 16
ORDINARY_WINDOWS = 200_000
TOXIC_BYTES = 1 << 13
FRAME = 100
WINDOW, STRIDE = 4, 2
#: Bytes of a match at least.
MATCH = 6
#: Bytes of a text that are looked through at once.
STRETCH = 1 << 20
LEVELS = (3, 4, 5, 6)
THRESHOLD = 0.7
#: Share of the learning rows that calibrates: one in CALIBRATE.
CALIBRATE = 4
#: ASCII characters that are neither digits nor letters, cut off the ends of a word.
_EDGE = bytes(c for c in range(33, 127) if not chr(c).isalnum())


def cores(data: bytes | None) -> list[bytes]:
    """Words without ASCII punctuation at their ends."""
    return [w for w in (x.strip(_EDGE) for x in words_of(data)) if w]


def contexts(data: bytes | None) -> set[tuple[bytes, bytes, bytes]]:
    """Different (word before, word, word after) of a text; nothing stands before the first and after the last."""
    w = [b"", *cores(data), b""]
    return set(zip(w, w[1:], w[2:], strict=False))


def windows(data: bytes | None) -> list[bytes]:
    w = words_of(data)
    return [b" " + b" ".join(w[i : i + WINDOW]) + b" " for i in range(0, max(1, len(w) - WINDOW + STRIDE), STRIDE)] if w else []


def _trained(samples: list[bytes], size: int, k: int, d: int) -> bytes:
    """Content of a dictionary that zstandard trains, or the samples themselves where they are too few for it."""
    try:
        return zstandard.train_dictionary(size, samples, k=k, d=d).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[-size:]


def _grams(data: np.ndarray) -> np.ndarray:
    """The MATCH bytes from each position on as one number."""
    n = max(0, len(data) - MATCH + 1)
    out = np.zeros(n, np.uint64)
    for i in range(MATCH):
        out |= data[i : i + n].astype(np.uint64) << np.uint64(8 * i)
    return out


class Grams:
    """A set of strings of MATCH bytes: a table of 2^16 hashes before, the sorted strings behind."""

    def __init__(self, found: np.ndarray) -> None:
        self.sorted = np.unique(found)
        self.table = np.zeros(1 << 16, bool)
        self.table[self._slot(self.sorted)] = True

    @staticmethod
    def _slot(x: np.ndarray) -> np.ndarray:
        return (x * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(48)

    def among(self, x: np.ndarray) -> np.ndarray:
        """Places of members in x."""
        at = np.flatnonzero(self.table[self._slot(x)])
        return at[self.sorted[np.minimum(np.searchsorted(self.sorted, x[at]), len(self.sorted) - 1)] == x[at]] if len(at) else at


def window_bounds(words: list[bytes]) -> tuple[bytes, np.ndarray, np.ndarray]:
    """The words with single spaces around, and where the windows of `windows` begin and end in that."""
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    first = np.arange(0, max(1, len(words) - WINDOW + STRIDE), STRIDE)
    return b" " + b" ".join(words) + b" ", np.concatenate(([0], ends))[first], ends[np.minimum(first + WINDOW, len(words)) - 1] + 1


class Distance:
    """Lengths of windows under two dictionaries of one size that differ in `toxic` alone."""

    def __init__(self, ordinary: bytes, toxic: bytes) -> None:
        self.ordinary, self.content = ordinary, toxic
        self.frame = ordinary[-FRAME:]
        cut = min(len(toxic), max(0, len(ordinary) - FRAME))
        body = ordinary[cut : len(ordinary) - len(self.frame)]
        contents = body + ordinary[:cut] + self.frame, body + toxic + self.frame
        self.plain, self.toxic = map(self._press, contents)
        # Strings of MATCH bytes that begin in the toxic content, but for places where both have the same.
        a, b = (_grams(np.frombuffer(x, np.uint8)) for x in contents)
        self.telling = Grams(b[a != b] if len(a) == len(b) else b)

    @staticmethod
    def _press(content: bytes) -> zstandard.ZstdCompressor:
        params = zstandard.ZstdCompressionParameters(
            window_log=17, hash_log=17, chain_log=17, search_log=5, min_match=6, target_length=0,
            strategy=zstandard.STRATEGY_GREEDY, write_content_size=0, write_checksum=0, write_dict_id=0,
        )
        raw = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        return zstandard.ZstdCompressor(dict_data=raw, compression_params=params)

    def of(self, window: bytes) -> int:
        framed = window + self.frame
        return len(self.plain.compress(framed)) - len(self.toxic.compress(framed))

    def meets(self, text: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Marks of the windows [first, last) of text that hold telling strings, with the frame behind."""
        at = np.concatenate([a + self.telling.among(_grams(text[a : a + STRETCH + MATCH - 1])) for a in range(0, len(text), STRETCH)])
        marks = np.searchsorted(at, first) < np.searchsorted(at, last - MATCH, "right")
        if len(self.frame) < MATCH:
            return np.ones_like(marks)
        for k in range(1, MATCH):  # the last k bytes of a window and the first of the frame
            g = np.full(len(last), int.from_bytes(self.frame[: MATCH - k], "little") << 8 * k, np.uint64)
            for i in range(k):
                g |= text[np.maximum(last - k + i, 0)].astype(np.uint64) << np.uint64(8 * i)
            marks[self.telling.among(g)] = True
        return marks

    def distances(self, data: bytes | None) -> np.ndarray:
        """One for each window; a text without any has one of 0."""
        words = words_of(data)
        if not words:
            return np.zeros(1, np.int64)
        text, first, last = window_bounds(words)
        found = np.zeros(len(first), np.int64)
        for i in np.flatnonzero(self.meets(np.frombuffer(text, np.uint8), first, last)).tolist():
            found[i] = self.of(text[first[i] : last[i]])
        return found

    def describe(self, data: bytes | None) -> list[float]:
        """Largest distance, mean of the three largest, counts and shares of windows at each level (as logarithms)."""
        found = self.distances(data)
        top = np.sort(found)[::-1][:3]
        counts = [(found >= t).sum() for t in LEVELS]
        return [float(top[0]), float(top.mean()), *(math.log1p(c) for c in counts), *(math.log1p(1000 * c / len(found)) for c in counts), math.log1p(len(found))]


def logistic(x: np.ndarray, y: np.ndarray, penalty: float = 1.0, steps: int = 40) -> np.ndarray:
    """Newton steps; the first column is the intercept and goes unpenalised."""
    w = np.zeros(x.shape[1])
    ridge = np.eye(len(w)) * penalty
    ridge[0, 0] = 1e-6
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge
        w -= np.linalg.solve(h + 1e-9 * np.eye(len(w)), x.T @ (p - y) + ridge @ w)
    return w


def best_cut(margins: np.ndarray, y: np.ndarray) -> float:
    """Margin from which rows count as toxic with the best F1, in the middle of the gap."""
    order = np.argsort(-margins, kind="stable")
    m, hits = margins[order], np.cumsum(y[order])
    f1 = 2 * hits / (np.arange(1, len(y) + 1) + y.sum())
    last = np.append(m[1:] < m[:-1], True)  # rows of one margin stand together
    at = int(np.argmax(np.where(last, f1, -1)))
    return float((m[at] + m[at + 1]) / 2) if at + 1 < len(m) else float(m[at])


class Calibration:
    """From the description of a text to its score."""

    def __init__(self, rows: list[tuple[list[float], int]]) -> None:
        x, y = np.array([d for d, _ in rows], float), np.array([k for _, k in rows], float)
        self.mean, self.scale = x.mean(axis=0), x.std(axis=0) + 1e-9
        self.weights, self.shift = np.zeros(x.shape[1] + 1), 0.0
        self.weights = logistic(self._columns(x), y)
        if 0 < y.sum() < len(y):
            self.shift = math.log(THRESHOLD / (1 - THRESHOLD)) - best_cut(self._columns(x) @ self.weights, y)

    def _columns(self, x: np.ndarray) -> np.ndarray:
        return np.concatenate((np.ones((len(x), 1)), (x - self.mean) / self.scale), axis=1)

    def score(self, d: list[float]) -> float:
        z = float((self._columns(np.array([d]))[0] * self.weights).sum()) + self.shift
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


class Model:
    """What goes to the executors; compressors are built where they are used."""

    def __init__(self, prior: float, ordinary: bytes = b"", toxic: bytes = b"", calibration: Calibration | None = None) -> None:
        self.prior, self.ordinary, self.toxic, self.calibration = prior, ordinary, toxic, calibration
        self.distance: Distance | None = None

    def score(self, data: bytes | None) -> float:
        if self.calibration is None:
            return self.prior
        if self.distance is None:
            self.distance = Distance(self.ordinary, self.toxic)
        return self.calibration.score(self.distance.describe(data))

    def __getstate__(self):
        return {**self.__dict__, "distance": None}


def learning_rows(docs: DataFrame, labels: DataFrame, column: str, mod: int, keep_out: int, limit: int) -> DataFrame:
    """(text, y, part): the learning texts, dealt evenly and written; part is the fold of a text."""
    spark = docs.sparkSession
    found = learning_texts(docs, labels, column, fold("doc_id", mod) != keep_out, limit)
    rows = found.select("text", "y", F.pmod("h", F.lit(CALIBRATE)).cast("int").alias("part"))
    return materialise(rows.repartition(max(8, spark.sparkContext.defaultParallelism)), "toxic-learn")


def word_table(rows: DataFrame) -> DataFrame:
    """(word, toxic, plain): different contexts of the word in texts of each class."""

    def cut(batches):
        for b in batches:
            seen = (set(), set())
            for text, y in zip(byte_column(b, "text"), b.column(1).to_pylist(), strict=True):
                seen[y].update(contexts(text))
            for y in (0, 1):
                found = list(seen[y])
                sides = [crc32(a + b"\n" + c) for a, _, c in found]
                cols = [pa.array([w for _, w, _ in found], pa.binary()), pa.array(sides, pa.int64()), pa.array([y] * len(found), pa.int32())]
                yield pa.RecordBatch.from_arrays(cols, ["word", "sides", "y"])

    found = rows.select("text", "y").mapInArrow(cut, "word binary, sides long, y int").distinct()
    return found.groupBy("word").agg(F.sum("y").cast("long").alias("toxic"), F.sum(1 - F.col("y")).cast("long").alias("plain"))


def telling_words(table: DataFrame, most: int = TOXIC_WORDS) -> tuple[list[tuple[bytes, int]], int]:
    """([(word, contexts in toxic texts)], the most telling first; contexts in ordinary texts)."""
    table = materialise(table, "toxic-words")
    total = table.agg(F.sum("toxic"), F.sum("plain")).first()
    n1, n0 = total[0] or 0, total[1] or 0
    if not n1 or not n0:
        return [], n0
    t, o = F.col("toxic"), F.col("plain")
    p = (t + o) / (n1 + n0)
    gain = 2 * (t * F.log(t / n1 / p) + F.when(o > 0, o * F.log(o / n0 / p)).otherwise(F.lit(0.0)))
    tells = table.where((t >= CONTEXTS) & (t / n1 > RATIO * (o + 0.5) / n0)).withColumn("gain", gain).where(F.col("gain") > GAIN)
    rows = tells.orderBy(F.desc("gain"), "word").limit(most).collect()
    return [(bytes(r["word"]), r["toxic"]) for r in rows], n0


def ordinary_windows(rows: DataFrame, total: int, most: int = ORDINARY_WINDOWS) -> list[bytes]:
    """About `most` different three-word windows of ordinary texts, never more, those of least hash; total: how many there are."""
    share = max(1, -(-total // most))

    def cut(batch):
        found = {b" " + b" ".join(w) + b" " for text in byte_column(batch, "text") for w in contexts(text)}
        yield pa.RecordBatch.from_arrays([pa.array([w for w in found if crc32(w) % share == 0], pa.binary())], ["w"])

    seen = map_rows(rows.where("y = 0").select("text"), "w binary", cut).distinct().limit(2 * most).collect()
    return sorted((bytes(r["w"]) for r in seen), key=lambda w: (crc32(w[::-1]), w))[:most]


def toxic_content(telling: list[tuple[bytes, int]]) -> bytes:
    samples = sorted(b" " + w + b" " for w, n in telling for _ in range(n))
    trained = _trained(samples, TOXIC_BYTES, 48, 6)
    return trained + b" " + b" ".join(w for w, _ in reversed(telling) if w not in trained) + b" "


def aligned(ordinary: bytes, content: bytes) -> bytes:
    """content with spaces before it, so that what it replaces in `ordinary` ends in a space as it does."""
    at = ordinary.find(b" ", len(content) - 1, max(0, len(ordinary) - FRAME))
    return b" " * (at + 1 - len(content)) + content if at >= 0 else content


def fit(docs: DataFrame, labels: DataFrame, mod: int = 3, keep_out: int = 1, max_train: int = MAX_TRAIN) -> Model:
    rows = learning_rows(docs, labels, "toxic", mod, keep_out, max_train)
    sizes = {r["y"]: r["count"] for r in rows.groupBy("y").count().collect()}
    toxic, plain = sizes.get(1, 0), sizes.get(0, 0)
    prior = toxic / (toxic + plain) if toxic + plain else 0.0
    build, check = rows.where("part > 0"), rows.where("part = 0")
    telling, total = telling_words(word_table(build)) if toxic and plain else ([], 0)
    if not telling:
        return Model(prior)
    ordinary = _trained(ordinary_windows(build, total), ORDINARY_BYTES, 64, 8)
    content = aligned(ordinary, toxic_content(telling))

    def describe(batches):
        distance = Distance(ordinary, content)
        for b in batches:
            found = [distance.describe(x) for x in byte_column(b, "text")]
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.list_(pa.float64())), b.column(1)], ["d", "y"])

    seen = sorted((list(r["d"]), r["y"]) for r in check.select("text", "y").mapInArrow(describe, "d array<double>, y int").collect())
    return Model(prior, ordinary, content, Calibration(seen)) if len({k for _, k in seen}) == 2 else Model(prior)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """docs (any columns, one named text) plus toxic_score."""
    docs = docs.drop("toxic_score")  # own name wins
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def one(batches):
        m = shared.value
        for b in batches:
            found = pa.array([m.score(x) for x in byte_column(b, "text")], pa.float64())
            yield pa.RecordBatch.from_arrays([*b.columns, found], [*b.schema.names, "toxic_score"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(one, f"{schema}, toxic_score double")


def toxicity_report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The contract's columns for every document."""
    return score(docs.select("doc_id", "text"), fit(docs, labels)).select(
        "doc_id",
        (fold("doc_id", 3) == 1).alias("held_out"),
        F.col("toxic_score").alias("score"),
        (F.col("toxic_score") >= THRESHOLD).cast("int").alias("predicted"),
    )
