"""The pipeline's stages over the smallest tables, each against what it must keep and remove."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from gridmatch.llm import common, near_duplicates, source_mix, toxicity

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    docs, out = common.table(spark, D, "documents"), {}
    out["documents"] = docs
    for name, stage in pipeline.STAGES:
        docs = common.cut(stage(spark, docs, D))
        out[name] = docs
    return out


def ids(df):
    return {r[0] for r in df.select("doc_id").collect()}


def test_columns(stages):
    names = [n for n, _ in pipeline.STAGES]
    assert names == ["toxicity", "near_duplicates", "substring_dedup", "source_mix", "packing"]
    for n in names[:-1]:
        assert stages[n].columns == stages["documents"].columns


def test_toxic_documents_go(spark, stages):
    model = toxicity.fit(stages["documents"], common.table(spark, D, "labels"))
    low = toxicity.score(stages["documents"], model, ["doc_id"]).filter(F.col("score") < toxicity.THRESHOLD)
    assert ids(low) == ids(stages["toxicity"])


def test_one_of_each_group_stays(stages):
    def shingles(text):
        w = (text or "").encode().split()
        w = [bytes(c + 32 if 65 <= c <= 90 else c for c in x) for x in w]
        return frozenset(zip(*(w[i:] for i in range(5)))) if len(w) >= 5 else frozenset([tuple(w)] if w else [])

    sets = {r["doc_id"]: shingles(r["text"]) for r in stages["toxicity"].select("doc_id", "text").collect()}
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    order = sorted(sets)
    for i, a in enumerate(order):
        for b in order[:i]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                up[y] = x
    assert ids(stages["near_duplicates"]) == {i for i in sets if find(i) == i}


def test_no_passage_stays_twice(stages):
    before = {r["doc_id"]: (r["text"] or "").encode().split() for r in stages["near_duplicates"].select("doc_id", "text").collect()}
    first, want = {}, {}
    for i in sorted(before):
        for j in range(len(before[i]) - 49):
            first.setdefault(tuple(before[i][j : j + 50]), i)
    for i, w in before.items():
        gone = {j + k for j in range(len(w) - 49) if first[tuple(w[j : j + 50])] < i for k in range(50)}
        want[i] = [x for j, x in enumerate(w) if j not in gone]
    after = {r["doc_id"]: (r["text"] or "").encode().split() for r in stages["substring_dedup"].select("doc_id", "text").collect()}
    assert after == want


def test_mix_reaches_its_targets(stages):
    plan = source_mix.plan(stages["substring_dedup"].select("doc_id", "source", "text"))
    want = {r["source"]: r["t"] for r in plan.groupBy("source").agg(F.max("target").alias("t")).collect()}
    got = {r["source"]: r["n"] for r in stages["source_mix"].groupBy("source").agg(F.sum(common.word_count(F.col("text"))).alias("n")).collect()}
    assert all(abs(got.get(s, 0) - t) <= 1 for s, t in want.items())


def test_every_token_is_packed_once(stages):
    packed = stages["packing"]
    assert ids(packed) == ids(stages["source_mix"])
    copies = stages["source_mix"].groupBy("doc_id").count()
    tokens = packed.filter("start = 0").groupBy("doc_id").agg(F.count("*").alias("n"))
    assert copies.join(tokens, "doc_id").filter("count <> n").isEmpty()
    s = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"), F.max(F.col("offset") + F.col("length")).alias("end"))
    assert s.filter("n > 4096 OR n <> end").isEmpty()


def test_run_leaves_only_its_result(spark):
    common.remove(spark, list(common.WRITTEN))
    out = pipeline.run(spark, D)
    assert out.count() > 0 and len(common.WRITTEN) == 1


def test_stages_of_an_empty_table(spark, tmp_path):
    for name in ("documents", "labels"):
        common.table(spark, D, name).filter("false").write.parquet(f"{tmp_path}/{name}.parquet")
    assert pipeline.run(spark, str(tmp_path)).count() == 0
