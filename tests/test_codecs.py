"""Coders, kernels, groups and baselines: exact and round-trip tests."""

import math
import random
from dataclasses import replace
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from basepack.functions import alphabet as A
from basepack.functions import coder as C
from basepack.operators import codec, context, general, grouping, nn, substitution
from basepack.plans import experiments, measures, model, train
from basepack.sources import tables as S


def sequences():
    rng = random.Random(42)
    r = lambda n: "".join(rng.choice("AGCT") for _ in range(n))
    block = r(200)
    return [
        "", "A", *(r(n) for n in (63, 64, 65, 127, 128, 129, 256)), "N" * 50, r(30) + "N" * 10 + r(90), r(128) + "NN" + r(126) + "N",
        "A" * 2000, "AG" * 500, r(1000), block + block, block + block[::-1].translate(str.maketrans("AGCT", "TCGA")), "AGCTAT",
    ]


@pytest.fixture(scope="module")
def seqs(spark):
    return spark.createDataFrame([("t", i, s) for i, s in enumerate(sequences())], "corpus string, seq_id long, bases string")


CODERS = {
    "context": lambda: codec.order_coder((1, 2, 9)),
    "multi": lambda: codec.model_coder(model.MULTI),
    "carry": lambda: codec.model_coder(replace(model.TINY, heads=2, block_order="standard", position="absolute")),
    "lockstep": lambda: codec.model_coder(replace(model.TINY, memory="features", segments=2, numeric_mode="lockstep")),
    "embedding": lambda: codec.model_coder(replace(model.TINY, input_coding="embedding", memory="none")),
    "bilstm": lambda: codec.model_coder(model.BILSTM),
}


@pytest.mark.parametrize("name", CODERS)
def test_round_trips(seqs, name):
    got = {r["seq_id"]: (r["n_bases"], r["digest"]) for r in codec.round_trip(seqs, CODERS[name](), 128, 16).collect()}
    want = {r["seq_id"]: (r["n_bases"], r["digest"]) for r in general.digests(seqs).collect()}
    assert got == want


@pytest.mark.parametrize("name", [*general.CODECS, "raw2"])
def test_archivers(seqs, name):
    back = general.raw2_back(general.raw2(seqs)) if name == "raw2" else general.decode(general.encode(seqs, name), name)
    assert {r["seq_id"]: r["bases"] for r in back.collect()} == dict(enumerate(sequences()))


def test_container_is_checked_and_repartitioned(seqs):
    known = A.split_unknown(seqs).select("corpus", "seq_id", "bases")
    c = codec.model_coder(model.MULTI)
    box = codec.compress(known, c, 128, 16)
    a = {r["seq_id"]: r["bases"] for r in codec.decompress(box, c, 16).collect()}
    b = {r["seq_id"]: r["bases"] for r in codec.decompress(box.repartition(7), c, 16).collect()}
    assert a == b
    with pytest.raises(Exception, match="another configuration"):
        codec.decompress(box, codec.model_coder(model.TINY), 16).collect()
    piece = codec.read_range(box, c, 14, 300, 400, 128, 16).first()["piece"]
    assert piece == sequences()[14][300:400]


def test_range_coder_is_near_entropy_and_carries():
    rng = np.random.default_rng(1)
    p = np.array([0.97, 0.01, 0.01, 0.01])
    data = rng.choice(4, (3, 20_000), p=p)
    counts = C.quantise(np.tile(p, (3, 1)))
    assert (counts.sum(axis=1) == C.TOTAL).all() and counts.min() >= 1
    out = C.encode_lanes(lambda prev: counts, data, np.array([20_000, 777, 0]))
    back = C.decode_lanes(lambda prev: counts, out, np.array([20_000, 777, 0]))
    assert (back[0] == data[0]).all() and (back[1, :777] == data[1, :777]).all() and out[2] == b""
    ideal = -np.log2(counts[0][data[0]] / C.TOTAL).sum()
    assert ideal <= 8 * len(out[0]) + 40 and 8 * len(out[0]) <= ideal * 1.001 + 64


def test_interval_fold_is_exact_on_dyadic_shares(spark):
    share = [Fraction(1, 2), Fraction(1, 4), Fraction(1, 8), Fraction(1, 16), Fraction(1, 16)]
    below = [sum(share[:i], Fraction(0)) for i in range(5)]
    low, width = Fraction(0), Fraction(1)
    for s in (2, 0, 1, 4):
        low, width = low + below[s] * width, width * share[s]
    steps = [(float(below[s]), float(share[s])) for s in (2, 0, 1, 4)]
    df = spark.createDataFrame([(steps,)], "steps array<struct<below:double,share:double>>").withColumn("iv", C.interval(F.col("steps")))
    bits, tag = C.shortest_tag(F.col("iv.low"), F.col("iv.width"))
    r = df.select("iv.low", "iv.width", bits.alias("bits"), tag.alias("tag")).first()
    assert (r["low"], r["width"]) == (float(low), float(width)) and width == math.prod(share[s] for s in (2, 0, 1, 4))
    assert r["low"] <= r["tag"] < r["low"] + r["width"] and r["bits"] == math.ceil(-math.log2(width)) + 1


@pytest.mark.parametrize("cfg", [
    replace(model.TINY, heads=2, input_coding="embedding"), replace(model.MULTI, block_order="standard"), model.LSTM, model.BILSTM,
])
def test_gradients(cfg):
    cfg = replace(cfg, numeric_mode="lockstep", dropout=0.0)
    rng = np.random.default_rng(0)
    w = {k: v + rng.normal(0, 0.05, v.shape) for k, v in nn.init(cfg).items()}
    codes, y = rng.integers(0, 4, (3, cfg.raw_context)), rng.integers(0, 4, 3)
    state = rng.normal(0, 1, (3, cfg.rows, cfg.d_model)) if cfg.kind == "carry" else None
    value = lambda w: nn.loss(nn.step(codes, state, w, cfg, nn.running(cfg))[0], y)
    t = {k: nn.Tensor(v) for k, v in w.items()}
    value(t).backward()
    for k, v in w.items():
        at = tuple(rng.integers(0, s) for s in v.shape)
        up, down = v.copy(), v.copy()
        up[at] += 1e-5
        down[at] -= 1e-5
        slope = (value(w | {k: up}) - value(w | {k: down})) / 2e-5
        assert abs(slope - t[k].grad[at]) < 1e-6, k


def test_rmsprop_by_hand():
    w = {"a": np.array([1.0])}
    o = train.RMSProp(0.1)
    o.step(w, {"a": np.array([2.0])})
    assert math.isclose(w["a"][0], 1 - 0.1 * 2 / (math.sqrt(0.01 * 4) + 1e-8), abs_tol=1e-12)


def test_training_lowers_loss(spark):
    rng = random.Random(0)
    df = spark.createDataFrame([(i, "".join(rng.choice(["AGCTT", "GGCA"]) for _ in range(300))) for i in range(8)], "seq_id long, bases string")
    cfg = replace(model.MULTI, block_order="standard", dropout=0.0)
    w, stats, h = train.fit(df, df, cfg, epochs=2, lanes=16, steps=60, rate=5e-3, partitions=2)
    assert h[-1][1] < h[0][1] and min(x[2] for x in h) < 1.9
    _, _, losses = train.fit_steps(df, cfg, steps=3, lanes=8)
    assert len(losses) == 3
    _, _, mixed = train.fit_mixed({"a": df, "b": df}, {"a": df, "b": df}, cfg, epochs=1, steps=5, partitions=2)
    assert len(mixed) == 1


def test_published_structure():
    assert model.PAPER.rows == 13 and model.MULTI.rows == 3
    assert model.cost_without_attention(model.PAPER) == 4_804_612
    w = nn.init(model.TINY)
    assert sum(v.size for v in w.values()) == sum(p for _, p, _ in model.model_cost(model.TINY))
    carry = sum(m for _, _, m in model.model_cost(model.PAPER))
    multi = sum(m for _, _, m in model.model_cost(replace(model.PAPER, ngram=2, byte_group=2)))
    assert multi < carry / 4
    assert grouping.length_for_budget(0.0006) == 213_334 and abs(128 / 213_000 - 0.0006) < 1e-5
    assert len(model.memory_grid()) == 4 and len(grouping.ablation_grid()) == 4


def test_memory_of_nothing_is_plain_attention():
    cfg = replace(model.TINY, position="none", numeric_mode="lockstep")
    w = nn.init(cfg)
    x = np.random.default_rng(0).normal(size=(2, 13, 16))
    assert np.allclose(nn.attention(x, None, w, cfg), nn.attention(x, np.zeros((2, 0, 16)), w, cfg))


def test_groups_words_fragments(spark, seqs):
    g = grouping.fixed_groups(seqs, 128)
    n = g.groupBy("seq_id").agg(F.sum("n_bases").alias("n"), F.max("n_bases").alias("m")).collect()
    assert all(r["n"] == len(sequences()[r["seq_id"]]) and r["m"] <= 128 for r in n)
    words = grouping.ngram_words(seqs.where("seq_id = 17"), 3).orderBy("i").collect()
    assert [r["word"] for r in words] == ["AGC", "TAT"]
    assert grouping.ngram_vocab(spark, 2).count() == 16
    f = {r["seq_id"]: r["fragment"] for r in grouping.initial_fragment(seqs).collect()}
    assert f[9] is None and "N" not in f[10] and len(f[10]) == 64
    x = np.arange(24.0).reshape(1, 6, 4)
    assert (grouping.byte_group(x, 2).reshape(-1) == x.reshape(-1)).all()
    assert grouping.MultiLevelPlan(128, 2, 2).apply(seqs).where("n_rows <> n_bases div 2 div 2").count() == 0


def test_repeats(spark):
    s = dict(enumerate(sequences()))
    df = spark.createDataFrame([(15, s[15]), (16, s[16])], "seq_id long, bases string")
    m = substitution.matches(df).where("len >= 100").collect()
    assert [(r["seq_id"], r["pos"], r["src"], r["len"]) for r in m] == [(15, 200, 0, 200)]
    assert substitution.palindromes(df.where("seq_id = 16")).count() >= 100
    assert substitution.dp_parse(df).where("seq_id = 15").first()["bits"] <= 2 * 200 + 24
    assert general.nml_blocks(df).count() == 2
    last = general.bwt_blocks(df).where("seq_id = 15 AND block = 0").first()["last"]
    assert general.bwt_inverse(last) == s[15][:60]


def test_text_formats(spark, tmp_path, seqs):
    p = tmp_path / "a.fa"
    p.write_text(">one x\nAGC\ntat\n>two\nGGG\n")
    spark.dataSource.register(S.FastaDataSource)
    want = [("one x", "AGCTAT"), ("two", "GGG")]
    assert sorted(map(tuple, spark.read.format("fasta").load(str(p)).collect())) == want
    assert sorted(map(tuple, S.read_fasta_text(spark, str(p)).collect())) == want
    S.write_fasta(seqs.where("seq_id = 17"), str(tmp_path / "out"))
    assert [tuple(r) for r in S.read_fasta_text(spark, str(tmp_path / "out")).collect()] == [("17", "AGCTAT")]
    w = nn.init(model.TINY)
    model.save(spark, w, str(tmp_path / "w"), "x")
    back = model.load(spark.read.parquet(str(tmp_path / "w")), "x")
    assert all((back[k] == w[k]).all() for k in w)


def test_measures(spark, seqs):
    box = codec.compress(A.split_unknown(seqs).select("corpus", "seq_id", "bases"), codec.order_coder((1,)), 512, 16)
    r = measures.bpb(box).first()
    assert 0 < r["bpb"] < 2.2 and measures.ratio(box).first()["ratio"] > 3.6
    assert measures.bpb_with_model(box, 100).first()["bpb_with_model"] > r["bpb"]
    assert measures.fragment_overhead(box).first()["overhead"] > 0
    assert measures.lossless(seqs, seqs).where("NOT lossless").count() == 0
    res = spark.createDataFrame([("h", "a", 0.0145, 60.0, 10), ("h", "b", 0.0075, 30.0, 10)], "corpus string, method string, bpb double, seconds double, n_bases long")
    x = measures.relative(res, "a").where("method = 'b'").first()
    assert math.isclose(x["saving"], 0.4828, abs_tol=1e-4) and x["speedup"] == 2
    assert measures.throughput(res).count() == 2 and measures.generalisation(res, res).where("gap <> 0").count() == 0


def test_ranges_of_a_long_sequence(spark):
    """Groups 9 and 10 share lane batches with groups that do not belong to the range."""
    rng = random.Random(3)
    texts = {1: "".join(rng.choice("AGCT") for _ in range(12 * 256 + 5)), 2: "".join(rng.choice("AGCT") for _ in range(900))}
    df = spark.createDataFrame([("c", i, t) for i, t in texts.items()], "corpus string, seq_id long, bases string")
    c = codec.order_coder((1, 2))
    box = codec.compress(df, c, 256, 8)
    for a, b in ((9 * 256, 10 * 256), (10 * 256 + 7, 10 * 256 + 9), (9 * 256 - 3, 11 * 256 + 4), (12 * 256, 12 * 256 + 5), (0, 1)):
        assert codec.read_range(box, c, 1, a, b, 256, 8).first()["piece"] == texts[1][a:b]
    assert codec.decode_groups(box, c, 8).count() == 13 + 4


def test_compression_has_as_many_tasks_as_shuffle_partitions(spark):
    old = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "13")
    try:
        df = spark.range(400).selectExpr("'c' corpus", "id seq_id", "repeat('AGCTTG', 40) bases")
        c = codec.order_coder((1,))
        p = codec.compress(df, c, 64, 4)._jdf.queryExecution().executedPlan().toString()
        assert "hashpartitioning(seq_id" in p and ", 13)" in p
        box = codec.compress(df, c, 64, 4)
        assert box.select("shard").distinct().count() == 13
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)


def test_map_kernels_equal_their_definition(spark):
    texts = ["", "a", "\u00e9\U0001f600 x", None, "long " * 500]
    df = spark.createDataFrame(list(enumerate(texts)), "i int, t string").repartition(2)
    for r in df.select("t", A.quad_map(F.col("t")).alias("q"), A.unpack(A.pack(A.quad_map(F.col("t")))).alias("u")).collect():
        if r["t"] is None:
            assert r["q"] is None and r["u"] is None
        else:
            want = "".join("AGCT"[x >> s & 3] for x in r["t"].encode() for s in (6, 4, 2, 0))
            assert r["q"] == want == r["u"]


def brute_parse(s, k, pointer):
    best = [0] * (len(s) + 1)
    for i in range(len(s) - 1, -1, -1):
        best[i] = best[i + 1] + 2
        for src in range(i):
            for m in range(1, len(s) - i + 1):
                if s[src + m - 1] != s[i + m - 1]:
                    break
                if m >= k:
                    best[i] = min(best[i], pointer + best[i + m])
    return best[0]


def test_cheapest_parse_equals_brute_force():
    rng = random.Random(7)
    for _ in range(60):
        s = "".join(rng.choice("AG") for _ in range(rng.randint(0, 40)))
        for k, pointer in ((3, 5), (4, 7)):
            assert substitution.cheapest_parse(s, k, pointer) == brute_parse(s, k, pointer)


def test_repeat_coders_give_back_every_base(spark):
    rng = random.Random(11)
    base = "".join(rng.choice("AGCT") for _ in range(320))
    near = "".join("A" if i % 40 == 0 else c for i, c in enumerate(base))
    texts = {1: base + near, 2: base, 3: "", 4: "AG" * 90, 5: "".join(rng.choice("AGCT") for _ in range(700))}
    df = spark.createDataFrame(list(texts.items()), "seq_id long, bases string").repartition(3)
    assert {r["seq_id"]: r["bases"] for r in substitution.expand(substitution.greedy_parse(df)).collect()} == texts
    coded = substitution.repeat_encode(df)
    assert {r["seq_id"]: r["bases"] for r in substitution.repeat_decode(coded.repartition(5)).collect()} == texts
    bits = {r["seq_id"]: r["n_bits"] for r in coded.collect()}
    assert bits[4] < 100 * 2
    blocks = substitution.repeat_blocks(df)
    back = {(r["seq_id"], r["b"]): r["block"] for r in substitution.repeat_blocks_back(blocks).collect()}
    assert back == {(i, b): t[32 * b : 32 * b + 32] for i, t in texts.items() for b in range(len(t) // 32)}
    assert blocks.where("seq_id = 2").agg(F.sum("bits")).first()[0] <= 10 * 24


def test_static_fragments(spark):
    df = spark.createDataFrame([(1, "AAAAGAAAAC" * 6), (2, ""), (3, "T"), (4, "AGCT" * 16)], "seq_id long, bases string")
    coded = codec.static_encode(df)
    assert {r["seq_id"]: r["bases"] for r in codec.static_decode(coded.repartition(3)).collect()} == {r["seq_id"]: r["bases"] for r in df.collect()}
    assert len(coded.where("seq_id = 1").first()["payload"]) < 60 // 4 < len(coded.where("seq_id = 4").first()["payload"]) + 2


def test_word_counts(spark):
    df = spark.createDataFrame([("AGCTAGC",), ("AG",), (None,), ("",)], "bases string")
    got = {r["word"]: r["n"] for r in context.word_counts(df, 2).collect()}
    assert got == {1: 3, 6: 2, 11: 1, 12: 1}


@pytest.mark.parametrize(("orders", "lanes"), [((1, 2, 4, 8), 3), ((1, 2, 3, 4, 6, 8), 1), ((2,), 700), ((8, 1), 1500)])
def test_context_coder_equals_its_definition(orders, lanes):
    """Counts of every step, lane by lane, from contexts spelt out; some contexts share slots from 1500 lanes on."""
    rng, steps = np.random.default_rng(6), 40
    codes = np.tile(rng.integers(0, 4, (1, steps)), (lanes, 1))
    codes[::2] = rng.integers(0, 2, (len(codes[::2]), steps))
    step = codec.OrderStep(orders, lanes, np.zeros((lanes, 0), np.int64))
    got = [step(codes[:, t - 1] if t else None) for t in range(steps)]
    assert got[0].shape == (lanes, 4)
    for lane in {0, lanes // 2, lanes - 1}:
        seen, score, past, probs = [{} for _ in orders], np.zeros(len(orders)), [0] * 8, None
        for t in range(steps):
            if t:
                c = codes[lane, t - 1]
                score = 0.98 * score + np.log2(probs[:, c])
                for table, k in zip(seen, keys, strict=True):
                    table.setdefault(k, np.zeros(4, np.float32))[c] += 1
                past = [*past[1:], int(c)]
            keys = [sum(4**i * past[-1 - i] for i in range(k)) for k in orders]
            keys = [k if 4**n <= step.slots else (k * 2654435761 >> 7) % step.slots for n, k in zip(orders, keys, strict=True)]
            probs = np.array([table.get(k, np.zeros(4)) + 1 / 16 for table, k in zip(seen, keys, strict=True)], float)
            probs /= probs.sum(axis=1, keepdims=True)
            weight = np.exp2(np.clip(score - score.max(), -40, 0))
            p = np.rint((probs * weight[:, None]).sum(axis=0) / weight.sum() * 65536) / 65536
            assert (got[t][lane] == C.quantise((p / p.sum())[None])[0]).all()


def test_quantising_columns_equals_rows():
    """Ties go to the lowest code; for columns as for rows."""
    p = np.concatenate((np.random.default_rng(2).dirichlet(np.ones(4), 500), np.full((1, 4), 0.25), np.eye(4), [[0.5, 0.5, 0, 0], [0, 0.5, 0.5, 0]]))
    assert (C.quantise_columns(p.T).T == C.quantise(p)).all()
    assert (C.cumulate(C.quantise(p))[:, -1] == C.TOTAL).all()


@pytest.mark.parametrize("cfg", [model.TINY, model.BYTE, model.MULTI, model.LSTM, model.BILSTM, *model.memory_grid().values()])
def test_validation_computes_a_row_once_and_equals_windows(cfg, monkeypatch):
    """The same bits as window by window, over stretches of any length, and the convolution runs once a stretch."""
    rng = np.random.default_rng(3)
    text, w = rng.integers(0, 4, (5, cfg.raw_context + 23)), nn.init(cfg, 3)
    stats = {"mean": rng.normal(0, 0.1, cfg.d_model), "var": np.full(cfg.d_model, 1.3)}
    state, bits = None, 0.0
    for t in range(23):
        logits, state = nn.step(text[:, t : t + cfg.raw_context], state, w, cfg, stats)
        bits += float(nn.loss(logits, text[:, t + cfg.raw_context])) * 5
    monkeypatch.setattr(nn, "features", None)
    for ahead in (1, 10, 256):
        monkeypatch.setattr(train, "AHEAD", ahead, raising=False)
        got, n = train.validate(text, w, stats, cfg)
        assert n == 115 and abs(got - bits) < 1e-9 * bits
    assert train.validate(text[:, : cfg.raw_context], w, stats, cfg) == (0.0, 0)


def test_training_reads_every_base_and_lanes_of_each_corpus():
    t = train.lane_text(["AGCT" * 50, "TT"], 4, 8)
    assert t.size >= 202 and (t.reshape(-1)[:202] == np.concatenate([codec.codes_of("AGCT" * 50), codec.codes_of("TT")])).all()
    both = train.side_by_side({"a": ["AG" * 100], "b": ["C" * 40]}, 4, 8)
    assert both.shape == (8, 50) and set(both[:4].reshape(-1)) == {0, 1} and set(both[4:].reshape(-1)) == {2}
    cfg = replace(model.MULTI, block_order="standard")
    w, stats = nn.init(cfg), nn.running(cfg)
    text = train.lane_text(["AGCT" * 100], 2, cfg.raw_context)
    bits, n = train.validate(text, w, stats, cfg)
    assert n == 2 * (text.shape[1] - cfg.raw_context) and bits > 0


def test_trainings_side_by_side_equal_trainings_one_by_one(spark, monkeypatch):
    """Every method on every corpus gets the weights that it would get alone; all trainings are begun before one has ended."""
    import threading
    rng = random.Random(1)
    parts = {}
    for corpus in ("a", "b"):
        df = spark.createDataFrame([(i, "".join(rng.choice("AGCT") for _ in range(300))) for i in range(20)], "seq_id long, bases string")
        parts[corpus] = {"train": df.where("seq_id < 15"), "val": df.where("seq_id >= 15")}
    monkeypatch.setattr(experiments, "LEARNED", {"carry": model.TINY, "conv_lstm": model.LSTM})
    fit, together = train.fit, threading.Barrier(4, timeout=60)

    def short(tr, va, cfg, **options):
        together.wait()
        return fit(tr, va, cfg, **(options | {"steps": 3, "lanes": 4}))

    monkeypatch.setattr(train, "fit", short)
    got = experiments._trained(parts)
    assert len(got) == 4
    for (corpus, name), (w, stats) in got.items():
        cfg = replace(experiments.LEARNED[name], block_order="standard")
        want, running, _ = fit(parts[corpus]["train"], parts[corpus]["val"], cfg, epochs=2, steps=3, lanes=4, rate=3e-3, partitions=2)
        assert all((w[k] == want[k]).all() for k in want) and all((stats[k] == running[k]).all() for k in running)


def test_scores_train_on_every_base_of_the_training_part(spark, monkeypatch):
    """Each epoch has an update for every base after the first context of a lane, and the trainings of t1_scores ask for that."""
    cfg = replace(model.TINY, block_order="standard")
    text, seen = np.random.default_rng(4).integers(0, 4, (3, cfg.raw_context + 130)), []
    learn = train.gradients

    def watched(w, stats, cfg, window, target, state, rng):
        seen.append((window.copy(), target.copy(), state is None))
        return learn(w, stats, cfg, window, target, state, rng)

    monkeypatch.setattr(train, "gradients", watched)
    train.walk(text, nn.init(cfg), nn.running(cfg), cfg, None, 1e-3, 1, 60)
    assert (np.stack([t for _, t, _ in seen], axis=1) == text[:, cfg.raw_context :]).all()
    assert (seen[0][0] == text[:, : cfg.raw_context]).all() and [f for _, _, f in seen] == [True] + [False] * 129
    asked = []
    monkeypatch.setattr(train, "fit", lambda tr, va, cfg, **options: asked.append(options["steps"]) or ({}, {}, []))
    df = spark.createDataFrame([(1, "AGCT")], "seq_id long, bases string")
    experiments._trained({"a": {"train": df, "val": df}})
    assert asked == [None] * len(experiments.LEARNED)


def test_recurrent_layer_equals_its_definition():
    rng = np.random.default_rng(5)
    x, w = rng.normal(size=(3, 7, 5)), {"x_b": rng.normal(size=(5, 16)), "h_b": rng.normal(size=(4, 16)), "g_b": rng.normal(size=16)}
    s = lambda v: 1 / (1 + np.exp(-v))
    h, c = np.zeros((3, 4)), np.zeros((3, 4))
    got = nn.lstm(x, w, "b", reverse=True)
    for t in reversed(range(7)):
        i, f, o, g = np.split(x[:, t] @ w["x_b"] + w["g_b"] + h @ w["h_b"], 4, axis=1)
        c = s(f + 1) * c + s(i) * np.tanh(g)
        h = s(o) * np.tanh(c)
        assert np.allclose(got[:, t], h, atol=1e-14)


@pytest.mark.parametrize("cfg", [model.MULTI, replace(model.TINY, block_order="standard"), model.LSTM, replace(model.SMALL, context=40), replace(model.TINY, position="none", memory="none")])
def test_epochs_are_judged_in_step_and_lanes_are_shared(cfg):
    """Several models over several shares of the lanes give what each gives alone, window by window."""
    rng = np.random.default_rng(8)
    text = rng.integers(0, 4, (6, cfg.raw_context + 19)).astype(np.uint8)
    models = [(nn.init(cfg, k), {"mean": rng.normal(0, 0.1, cfg.d_model), "var": np.full(cfg.d_model, 1.1 + k)}) for k in range(3)]
    shared = [train.validate_all(text[k::2], models, cfg) for k in range(2)]
    assert [n for _, n in shared] == [57, 57]
    for k, (w, stats) in enumerate(models):
        state, bits = None, 0.0
        for t in range(19):
            logits, state = nn.step(text[:, t : t + cfg.raw_context], state, w, cfg, stats)
            bits += float(nn.loss(logits, text[:, t + cfg.raw_context])) * 6
        assert abs(sum(b[k] for b, _ in shared) - bits) < 1e-9 * bits


def test_training_has_one_validation_for_all_epochs(spark, monkeypatch):
    """Its tasks are as many as there are cores, and the history is that of whole partitions."""
    rng = random.Random(3)
    df = spark.createDataFrame([(i, "".join(rng.choice("AGCT") for _ in range(400))) for i in range(40)], "seq_id long, bases string")
    jobs, plain = [], type(df).mapInArrow
    monkeypatch.setattr(type(df), "mapInArrow", lambda self, fn, schema: jobs.append((schema, self.rdd.getNumPartitions())) or plain(self, fn, schema))
    cfg = replace(model.MULTI, block_order="standard")
    w, stats, history = train.fit(df.where("seq_id < 20"), df.where("seq_id >= 20"), cfg, epochs=3, lanes=4, steps=5, rate=3e-3, partitions=2)
    assert [n for schema, n in jobs if "epoch" in schema] == [2 * (spark.sparkContext.defaultParallelism // 2)]
    parts: dict = {}
    for r in df.where("seq_id >= 20").selectExpr("seq_id", "bases", "pmod(hash(seq_id), 2) AS p").orderBy("seq_id").collect():
        parts.setdefault(r["p"], []).append(r["bases"])
    found = [train.validate(train.lane_text(x, 4, cfg.raw_context), w, stats, cfg) for x in parts.values()]
    assert len(history) == 3 and abs(sum(b for b, _ in found) / sum(n for _, n in found) - min(h[2] for h in history)) < 1e-9


@pytest.mark.parametrize("orders", [(1, 2, 4, 8), (0, 12)])
def test_contexts_in_the_jvm_give_the_bytes_of_the_lanes(spark, seqs, orders, monkeypatch):
    """Payloads, places and groups of both forms are the same, each reads the other's, and no task of Python codes."""
    known = A.split_unknown(seqs).select("corpus", "seq_id", "bases")
    rng = np.random.default_rng(9)
    long = spark.createDataFrame([("x", 99, codec.bases_of(rng.choice(4, 3000, p=[0.001, 0.9, 0.09, 0.009])))], known.schema)
    known = known.unionByName(long)
    coder, mine = codec.order_coder(orders), codec.Coder.in_jvm

    def here(on, fn, *args):
        monkeypatch.setattr(codec.Coder, "in_jvm", mine if on else lambda self, spark: False)
        return fn(*args)

    for group, lanes in ((128, 16), (1 << 20, 8)):
        a, b = (here(on, codec.compress, known, coder, group, lanes) for on in (True, False))
        assert "MapInArrow" not in a._jdf.queryExecution().executedPlan().toString()
        assert a.dtypes == b.select(*a.columns).dtypes and set(a.columns) == set(b.columns)
        want = {tuple(r) for r in b.select(*a.columns).collect()}
        assert {tuple(r) for r in a.collect()} == want and max(r[4] for r in want) == min(group, 3000)
        bases = {r["seq_id"]: r["bases"] for r in known.where("bases <> ''").collect()}
        for box, on in ((a, False), (b, True)):
            assert {r["seq_id"]: r["bases"] for r in here(on, codec.decompress, box, coder, lanes).collect()} == bases
    with pytest.raises(Exception, match="another configuration"):
        codec.decompress(codec.compress(known, coder, 128, 16), codec.order_coder((1, 3)), 16).collect()


def test_powers_and_logarithms_of_the_context_coder():
    x = np.concatenate((-np.random.default_rng(1).random(1000) * 40, [0, -0.5, -1, -40]))
    assert np.allclose(C.exp2_of(x), np.exp2(x), rtol=1e-15, atol=0) and C.exp2_of(np.zeros(1))[0] == 1
    p = np.concatenate((np.exp2(x), [1 / 3, 0.7071067811865475, 0.7071067811865476]))
    assert np.allclose(C.log2_of(p), np.log2(p), rtol=4e-16, atol=4e-16)
