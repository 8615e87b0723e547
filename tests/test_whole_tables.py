"""Queries go over all of their table."""

import numpy as np

from basepack import queries as K
from basepack.operators import general
from basepack.sources import tables as S

SF = "/root/testdata/sf0.001"


def whole(rows, column):
    out = {}
    for r in sorted(rows, key=lambda r: (r["seq_id"], r["block"])):
        out[r["seq_id"]] = out.get(r["seq_id"], "") + column(r)
    return out


def test_interval_blocks_give_back_every_base(spark):
    want = {r["seq_id"]: r["bases"] for r in S.event_seq(spark, SF).collect()}
    assert max(map(len, want.values())) > 24
    assert whole(K.Q["interval_blocks_decode"](spark, SF).collect(), lambda r: r["bases"]) == want


def test_interval_blocks_of_rare_bases_come_back(spark, tmp_path):
    # 13 rare events side by side among 4000: their interval is narrower than 2^-53.
    kinds = ["click"] * 3000 + ["purchase"] * 13 + ["error"] * 7 + ["view"] * 980
    rows = [(i, i, kind) for i, kind in enumerate(kinds)]
    spark.createDataFrame(rows, "event_id long, t long, event_type string").selectExpr(
        "event_id", "timestamp_seconds(t) AS ts", "1L AS user_id", "event_type").write.parquet(f"{tmp_path}/events.parquet")
    want = S.event_seq(spark, str(tmp_path)).first()["bases"]
    assert whole(K.Q["interval_blocks_decode"](spark, str(tmp_path)).collect(), lambda r: r["bases"]) == {1: want}


def test_block_sort_gives_back_every_base(spark):
    want = {r["seq_id"]: r["bases"] for r in S.bench_quad(spark, SF).collect()}
    assert whole(K.Q["bwt_blocks"](spark, SF).collect(), lambda r: general.bwt_inverse(r["last"])) == want


def test_latent_state_goes_over_every_segment(spark):
    rows = S.segments(spark, SF).orderBy("seg", "i").collect()
    segs: dict = {}
    for r in rows:
        segs.setdefault(r["seg"], []).append(r["vec"])
    assert len(segs) > 3
    got: dict = {}
    for r in K.Q["attend_latent_whole"](spark, SF).orderBy("seg", "i", "d").collect():
        got.setdefault(r["seg"], []).append(r["o"])
    state = np.empty((0, 64))
    for t in sorted(segs):
        q = np.array(segs[t])
        keys = np.concatenate((state, q))
        e = np.exp(q @ keys.T / 8)
        state = (e / e.sum(axis=1, keepdims=True)) @ keys
        assert np.allclose(state.ravel(), got.pop(t), atol=2e-6)
    assert not got


def test_nml_blocks_look_at_every_earlier_block(spark):
    first = "ACGGTTCAGATTACAGGCATCCGATGCAAGTC"
    s = first + "A" * 32 * 300 + first
    got = {r["seq_id"]: r["bits"] for r in general.nml_blocks(spark.createDataFrame([(1, s), (2, s[:-32])], "seq_id long, bases string")).collect()}
    assert got[1] - got[2] < 32  # a copy, not 64 bits and a flag
