"""Language-model scores from a subword lattice.

A word is spelt by the pieces of an existing vocabulary (a public SentencePiece file whose path is a
parameter; it is never trained). Every segmentation of the word counts: a forward recursion in log space
adds the probabilities of all of them, so the lattice gives the marginal probability of the spelling.
The file's scores are merge ranks r, so piece weights follow the rank law 1 / (r + 2.7), normalised over the
pieces, bytes covering whatever no piece spells; word starts are part of the pieces, so a text's marginal
is the product of its words' marginals.

Texts fall into classes, one for each of the most frequent `lang` values of the learning rows (one class without
them); a text's class is found from its own byte trigrams alone. The existing weights decide how a class is
segmented; expected piece counts of its learnt words then adapt the weights (the pieces stay): a first step over the
words seen `often` times, which are few and set the direction, and a second over all words. The spelling model is part of the base measure of what the corpus teaches:

    q(w)         = (1 - share) * spell_k(w) + share * count(w) / tokens
    P(w)         = (max(count_k(w) - D_k, 0) + D_k * types_k * q(w)) / tokens_k
    P(w | doc)   = (seen so far in the document(w) + rho * P(w)) / (tokens so far + rho)
    P(text)      = prior(k) * product of P(w | doc)

The discount D_k is n1 / (n1 + 2 n2), by how many types occur once and twice. All word forms sum to one over
all spellings, so summed over texts the probabilities are at most one (a text takes its one class, not the sum over
classes). A document's probability does not depend on the order of its words, so it is scored from word counts.

Counts are taken over all words of all documents (map-side combined). The most frequent words, `head` at
most whatever the corpus, are broadcast; all others are joined by shuffle, one row for each word of a
document. So frequent words are never a shuffle key.

Defined results: null, empty and blank texts are the end token alone; null ids belong to fold 0; repeated
rows are scored and learned from as they come; very long texts are read whole, in blocks; an empty table gives an empty
result; columns other than doc_id, text and lang are not read.
"""

from __future__ import annotations

import math
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ASCII_LOWER, blocks, byte_column, fold, map_rows, materialise, words_of

VOCABULARY = "/opt/tokenizers/piece_bpe_32k.model"
HEAD = 250_000
RHO = 3000.0
#: Share of the pooled word frequencies in the base measure.
SHARE = 0.05
CLASSES = 8
#: Words seen this often set the direction of the adaptation.
OFTEN = 16
#: Hashed byte trigrams that tell classes apart.
BINS = 4096
END = b""
LN10 = math.log(10)


def load_pieces(path: str = VOCABULARY) -> dict[bytes, float]:
    """Piece -> log probability; read on the driver, bounded by the vocabulary."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    ranks = {}
    for i in range(sp.get_piece_size()):
        piece = sp.id_to_piece(i)
        if sp.is_byte(i):
            ranks[bytes([int(piece[3:5], 16)])] = sp.get_piece_size()
        elif not (sp.is_control(i) or sp.is_unknown(i)):
            ranks[piece.encode()] = 1 - sp.get_score(i)
    mark = "▁".encode()
    for b in range(256):  # every byte must be spellable
        ranks.setdefault(bytes([b]), sp.get_piece_size())
    ranks.setdefault(mark, sp.get_piece_size())
    total = sum(1 / (r + 2.7) for r in ranks.values())
    return {p: -math.log((r + 2.7) * total) for p, r in ranks.items()}


_SHORT = (1, 2, 3)


class Spelling:
    """All segmentations of words into pieces, weighted in log space."""

    def __init__(self, pieces: dict[bytes, float]) -> None:
        self.pieces = pieces
        self.mark = "▁".encode()
        longer: dict[bytes, set[int]] = {}
        for p in pieces:
            if len(p) > 3:
                longer.setdefault(p[:3], set()).add(len(p))
        #: First three bytes -> lengths of the pieces that begin so.
        self.longer = {k: tuple(sorted(v)) for k, v in longer.items()}

    def forward(self, word: bytes) -> tuple[list[float], list[tuple[int, int, bytes, float]]]:
        """Log mass of all segmentations of each prefix of mark + word, and the pieces that take part."""
        text = self.mark + word
        n = len(text)
        mass = [-math.inf] * (n + 1)
        mass[0] = 0.0
        edges = []
        get, longer = self.pieces.get, self.longer
        for i in range(n):
            here = mass[i]
            if here == -math.inf:
                continue
            for size in _SHORT + longer.get(text[i : i + 3], ()):
                j = i + size
                if j > n:
                    break
                piece = text[i:j]
                w = get(piece)
                if w is None:
                    continue
                edges.append((i, j, piece, w))
                new, old = here + w, mass[j]
                if new > old:
                    new, old = old, new
                mass[j] = old + math.log1p(math.exp(new - old)) if new - old > -40.0 else old
        return mass, edges

    def log_prob(self, word: bytes) -> float:
        """Marginal log probability of the spelling. The end token is the mark alone."""
        text = self.mark + word
        n = len(text)
        none, log1p, exp = -math.inf, math.log1p, math.exp
        mass = [none] * (n + 1)
        mass[0] = 0.0
        get, longer = self.pieces.get, self.longer.get
        for i in range(n):
            here = mass[i]
            if here == none:
                continue
            for size in _SHORT + longer(text[i : i + 3], ()):
                j = i + size
                if j > n:
                    break
                w = get(text[i:j])
                if w is not None:
                    new, old = here + w, mass[j]
                    if new > old:
                        new, old = old, new
                    # old is the larger one now
                    mass[j] = old + log1p(exp(new - old)) if new - old > -40.0 else old
        return mass[n]

    def expect(self, word: bytes, total: dict[bytes, float]) -> None:
        """Add how often each piece is expected in the word, over its segmentations."""
        mass, edges = self.forward(word)
        back = [0.0] * len(mass)  # backward mass over the total, in plain numbers
        back[-1] = 1.0
        if mass[-1] < -500.0:
            return self._expect_log(mass, edges, total)
        for i, j, piece, w in reversed(edges):
            if back[j]:
                back[i] += back[j] * math.exp(w)
        # mass and back multiply to the posterior of an edge.
        whole = mass[-1]
        for i, j, piece, w in edges:
            if back[j]:
                total[piece] = total.get(piece, 0.0) + math.exp(mass[i] + w - whole) * back[j]
        return None

    def _expect_log(self, mass, edges, total) -> None:
        back = [-math.inf] * len(mass)
        back[-1] = 0.0
        for i, j, _, w in reversed(edges):
            if back[j] > -math.inf:
                new, old = back[j] + w, back[i]
                hi, lo = max(new, old), min(new, old)
                back[i] = hi + (math.log1p(math.exp(lo - hi)) if lo > -math.inf else 0.0)
        for i, j, piece, w in edges:
            if back[j] > -math.inf:
                total[piece] = total.get(piece, 0.0) + math.exp(mass[i] + w + back[j] - mass[-1])


class Classes:
    """Which class a text belongs to: the most likely one by hashed byte trigrams. Log shares are whole multiples of
    1 / 1024, whose sums are exact in any order, so that the choice is the same on every machine."""

    def __init__(self, log_shares: np.ndarray) -> None:
        self.log_shares = np.rint(1024 * log_shares)  # BINS x classes

    @property
    def n(self) -> int:
        return self.log_shares.shape[1]

    def of(self, data: bytes | None) -> int:
        if self.n == 1 or not data:
            return 0
        return int(np.argmax(trigrams(data).astype(float) @ self.log_shares))


def trigrams(data: bytes) -> np.ndarray:
    """How often each bin occurs; A-Z in lower case, in stretches of bounded size."""
    found = np.zeros(BINS, np.int64)
    text = np.frombuffer(data.translate(ASCII_LOWER), np.uint8)
    for i in range(0, max(0, len(text) - 2), 1 << 20):
        x = text[i : i + (1 << 20) + 2].astype(np.uint32)
        h = ((x[:-2] << 16) | (x[1:-1] << 8) | x[2:]) * np.uint32(2654435761)
        found += np.bincount(h >> np.uint32(20), minlength=BINS)
    return found


def fit_classes(docs: DataFrame, mod: int, keep_out: int, most: int = CLASSES) -> Classes:
    """docs: doc_id, text, lang. Trigram counts of all learning rows with one of the `most` most frequent languages."""
    one_class = Classes(np.zeros((BINS, 1)))
    learn = docs.where((fold("doc_id", mod) != keep_out) & F.col("lang").isNotNull() & F.col("text").isNotNull())
    names = [r["lang"] for r in learn.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(most).collect()]
    if len(names) < 2:
        return one_class
    number = {x: k for k, x in enumerate(names)}

    def count(batches):
        total = np.zeros((len(number), BINS), np.int64)
        for b in batches:
            for text, lang in zip(byte_column(b, "text"), b.column(1).to_pylist(), strict=True):
                total[number[lang]] += trigrams(text)
        k, at = np.nonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(at, pa.int32()), pa.array(total[k, at])], ["k", "bin", "c"])

    rows = learn.where(F.col("lang").isin(names)).select("text", "lang").mapInArrow(count, "k int, bin int, c long")
    total = np.full((BINS, len(names)), 0.5)
    for r in rows.groupBy("k", "bin").agg(F.sum("c").alias("c")).collect():  # at most classes x bins
        total[r["bin"], r["k"]] += r["c"]
    return Classes(np.log(total / total.sum(axis=0)))


def adapt(vocab: DataFrame, pieces: dict[bytes, float], now: list[dict[bytes, float]], strength: float = 0.005) -> list[dict[bytes, float]]:
    """Piece weights of each class, from the existing weights and what those of now make expected in the words of vocab,
    each word once. At most one row a class, piece and task is sent on; no piece is added or dropped."""
    shared = vocab.sparkSession.sparkContext.broadcast(now)
    classes = len(now)

    def one(batches):
        models, totals = [Spelling(p) for p in shared.value], [{} for _ in range(classes)]
        for b in batches:
            for w, k in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                models[k].expect(w, totals[k])
        for k, total in enumerate(totals):
            cols = [pa.array([k] * len(total), pa.int32()), pa.array(list(total), pa.binary()), pa.array(list(total.values()), pa.float64())]
            yield pa.RecordBatch.from_arrays(cols, ["k", "piece", "e"])

    seen = vocab.select("word", "k").mapInArrow(one, "k int, piece binary, e double")
    found: list[dict[bytes, float]] = [{} for _ in range(classes)]
    for r in seen.groupBy("k", "piece").agg(F.sum("e").alias("e")).collect():  # at most classes x pieces
        found[r["k"]][bytes(r["piece"])] = r["e"]
    out = []
    for f, w_now in zip(found, now, strict=True):
        total = sum(f[p] for p in sorted(f))
        out.append({p: math.log(strength * math.exp(w) + (1 - strength) * f.get(p, 0.0) / total) for p, w in pieces.items()} if total else w_now)
    return out


def word_counts(docs: DataFrame, classes: Classes, mod: int, keep_out: int) -> DataFrame:
    """(word, c, by): count in the learning documents of every word of any document, the end included, and the same
    for each class in which it occurs, as (k, n)."""
    slim = docs.select(F.when(fold("doc_id", mod) != keep_out, 1).otherwise(0).alias("learn"), "text")
    shared = docs.sparkSession.sparkContext.broadcast(classes)
    every = range(classes.n)

    def count(batches):
        model = shared.value
        total, other = [Counter() for _ in every], [set() for _ in every]
        for b in batches:
            for learn, text in zip(b.column(0).to_pylist(), byte_column(b, "text"), strict=True):
                words, k = words_of(text), model.of(text)
                if learn:
                    total[k].update(words)
                    total[k][END] += 1
                else:
                    other[k].update(words)
                    other[k].add(END)
            if sum(map(len, total)) + sum(map(len, other)) > 100_000:  # bounded memory: send on what there is
                yield from rows(total, other)
                total, other = [Counter() for _ in every], [set() for _ in every]
        yield from rows(total, other)

    def rows(total, other):
        for k in every:
            new = other[k].difference(total[k])
            words, n = [*total[k], *new], [*total[k].values(), *([0] * len(new))]
            yield pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), pa.array([k] * len(n), pa.int32()), pa.array(n, pa.int64())], ["word", "k", "n"])

    found = slim.mapInArrow(count, "word binary, k int, n long").groupBy("word").agg(
        F.sum("n").alias("c"), *[F.sum(F.when(F.col("k") == k, F.col("n"))).alias(f"n{k}") for k in every]
    )
    by = F.filter(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"n{k}").alias("n")) for k in every]), lambda x: x["n"].isNotNull())
    return found.select("word", "c", by.alias("by"))


def spelt(vocab: DataFrame, weights: list[dict[bytes, float]]) -> DataFrame:
    """(word, k, c, n, s): s is the log probability of the spelling in class k."""
    shared = vocab.sparkSession.sparkContext.broadcast(weights)

    def one(batches):
        models = [Spelling(p) for p in shared.value]
        for b in batches:
            s = [models[k].log_prob(w) for w, k in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(s, pa.float64())], ["word", "k", "c", "n", "s"])

    return vocab.mapInArrow(one, "word binary, k int, c long, n long, s double")


class Words:
    """log P(w) of words of one or more classes, from class facts of fixed size."""

    def __init__(self, tokens: int, classes: int, facts: list, share: float) -> None:
        size, types = np.zeros(classes), np.zeros(classes)
        discount = np.full(classes, 0.5)
        for k, n, v, n1, n2 in facts:
            size[k], types[k] = n, v
            if n1 and n2:
                discount[k] = n1 / (n1 + 2 * n2)
        self.discount = np.where(size > 0, discount, 0.0)
        self.size = np.maximum(size, 1)
        #: Mass that goes to the base measure; all of it where a class has learnt nothing.
        self.spread = np.where(size > 0, discount * types / self.size, 1.0)
        self.tokens, self.share = max(tokens, 1), share if tokens else 0.0

    def log_p(self, k, c, n, s) -> np.ndarray:
        seen = np.maximum(n - self.discount[k], 0) / self.size[k] + self.spread[k] * self.share * c / self.tokens
        with np.errstate(divide="ignore"):
            return np.logaddexp(np.log(seen), np.log(self.spread[k] * (1 - self.share)) + s)


def rising(log_x: np.ndarray, times: np.ndarray) -> np.ndarray:
    """log of x (x + 1) ... (x + times - 1)."""
    out = log_x.copy()
    more = np.flatnonzero(times > 1)
    small = more[times[more] <= 64]
    for i in range(1, int(times[small].max(initial=1))):
        on = small[times[small] > i]
        out[on] += np.log(np.exp(log_x[on]) + i)
    for i in more[times[more] > 64]:
        out[i] += np.log(np.exp(log_x[i]) + np.arange(1, times[i])).sum()
    return out


def score(docs: DataFrame, mod: int = 5, keep_out: int = 1, vocabulary: str = VOCABULARY, head: int = HEAD, rho: float = RHO, share: float = SHARE, often: int = OFTEN) -> DataFrame:
    """docs: doc_id, text and, if there is one, lang. The contract's columns for every row."""
    spark = docs.sparkSession
    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit(None).cast("string")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", lang.alias("lang"))
    classes = fit_classes(docs, mod, keep_out)
    docs = docs.drop("lang")
    counts = materialise(word_counts(docs, classes, mod, keep_out), "lattice-counts")
    flat = counts.select("word", F.explode("by").alias("x"), "c").select("word", "x.k", "c", "x.n")
    pieces = load_pieces(vocabulary)
    weights = adapt(flat.where(F.col("n") >= often), pieces, [pieces] * classes.n)
    weights = adapt(flat.where("n > 0"), pieces, weights)
    vocab = materialise(spelt(flat, weights), "lattice-vocab")
    facts = counts.agg(F.sum("c"), F.count(F.when(F.col("c") > 0, 1))).first()
    n, v = facts[0] or 0, facts[1]
    ones = [F.count(F.when(cond, 1)) for cond in (F.col("n") > 0, F.col("n") == 1, F.col("n") == 2)]
    model = Words(n, classes.n, [tuple(r) for r in vocab.groupBy("k").agg(F.sum("n"), *ones).collect()], share)
    ends = {r["k"]: r["n"] for r in vocab.where(F.col("word") == F.lit(END)).collect()}  # learning documents of each class
    prior = np.log(np.array([ends.get(k, 0) + 1.0 for k in range(classes.n)]) / (sum(ends.values()) + classes.n))
    # The lowest count of the words to broadcast: as many as `head` allows, in steps of two.
    steps = [max(1, n >> k) for k in range(6, 40)]
    sizes = vocab.agg(*[F.count(F.when(F.col("n") >= c, 1)).alias(f"s{i}") for i, c in enumerate(steps)]).first()
    least = min([c for i, c in enumerate(steps) if sizes[f"s{i}"] <= head], default=n + 1)
    known: list[dict] = [{} for _ in range(classes.n)]  # word -> column of terms
    terms, number = [np.zeros((2, 0))], 0
    for b in vocab.where(F.col("n") >= least).toArrow().to_batches():
        c, m, s = (b.column(i).to_numpy().astype(float) for i in (2, 3, 4))
        k = b.column(1).to_numpy()
        terms.append(np.stack((np.log10(c + 0.5), model.log_p(k, c, m, s))))
        for w, i in zip(b.column(0).to_pylist(), k.tolist(), strict=True):
            known[i][w] = number
            number += 1
    shared = spark.sparkContext.broadcast((classes, known, np.concatenate(terms, axis=1)))
    base = math.log10(n + 0.5 * (v + 1))

    def log_terms(log_p, times):
        return rising(math.log(rho) + log_p, times)

    def first(batch):
        """What the broadcast words give; the rest as a list of (word, times)."""
        texts = byte_column(batch, "text")
        for a, z in blocks([len(x or b"") for x in texts]):
            yield first_block(batch.column(0)[a:z], texts[a:z])

    def first_block(ids, texts):
        find, known, terms = shared.value
        total, classes_, hits, times, hit_cuts = [], [], [], [], [0]
        tail_w, tail_t, cuts = [], [], [0]
        for text in texts:
            words = Counter(words_of(text))
            words[END] += 1
            k = find.of(text)
            seen = known[k]
            for w, t in words.items():
                if (hit := seen.get(w)) is not None:
                    hits.append(hit)
                    times.append(t)
                else:
                    tail_w.append(w)
                    tail_t.append(t)
            cuts.append(len(tail_w))
            hit_cuts.append(len(hits))
            total.append(words.total())
            classes_.append(k)
        row = np.repeat(np.arange(len(texts)), np.diff(hit_cuts))
        log_c, log_p = terms[:, np.array(hits, np.int64)]
        t, size, k = np.array(times, np.int64), np.array(total, np.int64), np.array(classes_, np.int64)

        def summed(x):
            return np.bincount(row, x, len(texts))

        lp = prior[k] + summed(log_terms(log_p, t)) - rising(np.full(len(size), math.log(rho)), size)
        tail = pa.StructArray.from_arrays([pa.array(tail_w, pa.binary()), pa.array(tail_t, pa.int64())], ["w", "t"])
        cols = [ids, pa.array(size), pa.array(summed(t).astype(np.int64)), pa.array(summed(t * log_c) - base * size), pa.array(lp), pa.array(k, pa.int32())]
        cols.append(pa.ListArray.from_arrays(pa.array(cuts, pa.int32()), tail))
        return pa.RecordBatch.from_arrays(cols, ["doc_id", "n_tokens", "n_known", "base", "lp", "k", "tail"])

    # Numbers of rows are fixed by being written.
    scored = materialise(
        map_rows(docs, "doc_id long, n_tokens long, n_known long, base double, lp double, k int, tail array<struct<w:binary,t:long>>", first)
        .withColumn("row", F.monotonically_increasing_id()),
        "lattice-rows",
    )
    lookup = scored.select("row", "k", F.explode("tail").alias("x")).select("row", "k", F.col("x.w").alias("word"), F.col("x.t").alias("t"))
    found = lookup.join(vocab, ["word", "k"]).select("row", "k", "c", "n", "s", "t")

    def rest(batches):
        for b in batches:
            c, m, s = (b.column(i).to_numpy().astype(float) for i in (2, 3, 4))
            k, t = b.column(1).to_numpy(), b.column(5).to_numpy()
            cols = [b.column(0), pa.array(np.where(c > 0, t, 0)), pa.array(t * np.log10(c + 0.5)), pa.array(log_terms(model.log_p(k, c, m, s), t))]
            yield pa.RecordBatch.from_arrays(cols, ["row", "known", "b", "l"])

    more = found.mapInArrow(rest, "row long, known long, b double, l double").groupBy("row").agg(
        F.sum("known").alias("known"), F.sum("b").alias("b"), F.sum("l").alias("l")
    )
    zero = F.lit(0)
    return scored.drop("tail", "k").join(more, "row", "left").select(
        "doc_id",
        (fold("doc_id", mod) == keep_out).alias("held_out"),
        "n_tokens",
        (F.col("n_known") + F.coalesce("known", zero)).alias("n_known"),
        F.lit(n).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("b", F.lit(0.0))).alias("base_score"),
        ((F.col("lp") + F.coalesce("l", F.lit(0.0))) / LN10).alias("score"),
    )
