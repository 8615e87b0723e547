"""The pipeline's decisions, stage by stage, against direct checks."""

import random
from collections import Counter

import corpus_pipeline
from basepack.llm import decontaminate, simhash
from basepack.llm.common import materialise, table

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = table(spark, SF, "documents")
    seen = {"start": docs}
    for name, stage in corpus_pipeline.STAGES:
        out = materialise(stage(spark, docs, SF), "test")
        if name != "mixing":
            assert out.columns == seen["start"].columns
        assert 0 < out.count() <= docs.count()
        seen[name] = docs = out
    c = Counter(r["component_id"] for r in simhash.near_duplicates(seen["quality"]).collect())
    assert seen["near_duplicates"].count() == len(c)
    one = [x["text"] for x in seen["substrings"].collect()]
    windows = Counter(t.encode()[i : i + 200] for t in one for i in range(len(t.encode()) - 199))
    assert not [w for w, n in windows.items() if n > 1]  # joins of what is left make no new repeats here
    left = decontaminate.contamination(spark, seen["decontamination"], table(spark, SF, "benchmark"))
    assert left.where("contaminated").count() == 0
    mix = seen["mixing"].groupBy("source").agg({"mix_taken": "sum", "mix_target": "max", "mix_size": "max"}).collect()
    for r in mix:
        assert abs(r["sum(mix_taken)"] - r["max(mix_target)"]) <= r["max(mix_size)"]


def test_stages_on_awkward_rows(spark, tmp_path):
    """Null and repeated ids, null, empty and long texts, repeated rows, columns of the names that operators use; empty tables."""
    rng = random.Random(6)

    def words(n):
        return " ".join("".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(2, 9))) for _ in range(n))

    long, item = words(4000), words(20)
    texts = [None, "", long, words(60), words(60), words(80) + " " + item, *[words(70) for _ in range(8)]]
    rows = [(i, t) for i, t in enumerate(texts)] + [(None, words(50)), (None, words(50)), (3, words(50)), (4, texts[4]), (4, texts[4])]
    full = [(i, t, "en", "s" if k % 2 else None, len(t or ""), k, "x", k, "y") for k, (i, t) in enumerate(rows)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, fm_score int, contaminated string, rest int, head string"
    docs = spark.createDataFrame(full, schema)
    labels = spark.createDataFrame([(i, 1) for i in range(14)] + [(None, 0), (100, 0)], "doc_id long, quality int")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    for start in (docs, docs.limit(0)):
        now = start
        for name, stage in corpus_pipeline.STAGES:
            out = materialise(stage(spark, now, str(tmp_path)), "test")
            assert out.columns[: len(docs.columns)] == docs.columns and (name == "mixing" or len(out.columns) == len(docs.columns))
            got = out.select("n_chars", "fm_score", "contaminated", "rest", "head").collect()
            assert all((r["contaminated"], r["head"]) == ("x", "y") and r["fm_score"] == r["rest"] for r in got)
            if name == "quality" and start is docs:
                assert len(got) == len(rows)  # every label is good, so nothing goes
            if name == "near_duplicates" and start is docs:
                kept = Counter((r["doc_id"], r["text"]) for r in out.collect())
                want = {(i, t) for i, t in rows if t}  # no two texts are alike but the copies
                assert {k: v for k, v in kept.items() if k[1]} == dict.fromkeys(want, 1) and len(kept) == len(want) + 1
            if name == "decontamination" and start is docs:
                assert not [r for r in out.collect() if r["text"] and item in r["text"]]
            now = out
        assert start is docs or now.count() == 0
