"""Training-data operators do the whole of their job: no row, word or class is left out."""

import random
from collections import Counter

import pytest

from basepack.llm import lattice, simhash


def test_lattice_adapts_to_every_learnt_word(spark, monkeypatch):
    """Expected piece counts come from all words of the learning rows, those seen once included."""
    rows = [(i, "often " * 20 + f"twice{i // 2} single{'abcdefghij'[i % 10]}{i}") for i in range(40)]
    learn = spark.createDataFrame(rows, "doc_id long, text string").where((lattice.fold("doc_id", 5) != 1)).collect()
    c = Counter(w for r in learn for w in [*r["text"].encode().split(), lattice.END])
    assert min(c.values()) == 1
    pieces = lattice.load_pieces()

    def step(now, words, strength=0.005):
        total: dict = {}
        for w in words:
            lattice.Spelling(now).expect(w, total)
        whole = sum(total.values())
        return {p: strength * lattice.math.exp(x) + (1 - strength) * total.get(p, 0.0) / whole for p, x in pieces.items()}

    want = step({p: lattice.math.log(x) for p, x in step(pieces, [w for w, n in c.items() if n >= 16]).items()}, c)
    used = []
    spelt = lattice.spelt
    monkeypatch.setattr(lattice, "spelt", lambda vocab, weights: used.append(weights) or spelt(vocab, weights))
    assert lattice.score(spark.createDataFrame(rows, "doc_id long, text string")).count() == len(rows)
    assert {p: lattice.math.exp(x) for p, x in used[0][0].items()} == pytest.approx(want, rel=1e-6)


def test_keep_one_keeps_one_of_every_class(spark):
    """Null ids on unrelated texts, one id on texts of several classes, an id that heads one class and is in another."""
    rng = random.Random(5)

    def words():
        return " ".join(rng.choice("abcdefghijklmnop") * rng.randint(1, 9) for _ in range(80))

    a, b, c, d, e = (words() for _ in range(5))
    rows = [(None, words()) for _ in range(6)] + [(7, a), (7, b), (7, c), (3, b), (9, c), (9, a), (None, a), (None, d), (None, d), (11, e), (11, e)]
    rows += [(None, None), (None, ""), (12, " ")]
    docs = spark.createDataFrame([(*r, i) for i, r in enumerate(rows)], "doc_id long, text string, n int").repartition(3)
    kept = simhash.keep_one(docs).collect()
    every = Counter(simhash.fingerprint((t or "").encode()) for _, t in rows)
    assert all((x ^ y).bit_count() > 3 for x in every for y in every if x != y)  # a fingerprint is a class here
    assert Counter(simhash.fingerprint((r["text"] or "").encode()) for r in kept) == Counter(list(every))
    first = {r["text"]: r["doc_id"] for r in kept}
    assert (first[a], first[b], first[c], first[d], first[e], first[" "]) == (7, 3, 7, None, 11, 12)
    assert set(kept[0].asDict()) == {"doc_id", "text", "n"}
