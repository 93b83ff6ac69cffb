"""Operators against brute force on small fixtures: nulls, empty and long texts, ties, repeated
rows, empty tables and extra columns."""

import hashlib
import itertools
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from gridmatch.llm import chat_format, license_scan, near_duplicates, nearest, packing, quality_rules, source_mix, substring_dedup, toxicity, web_archive
from gridmatch.llm.components import components
from gridmatch.llm.fm_index import Index

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double"


def words_of(text):
    return (text or "").encode().split()


def make_docs():
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(rng.randint(1, 4)))
    base = [" ".join(word() for _ in range(rng.choice([5, 60, 140]))) for _ in range(30)]
    passage = " ".join(word() for _ in range(70))
    texts = base + base[:10]
    for t in base[:12]:
        w = t.split()
        w[rng.randrange(len(w))] = "changed"
        texts.append("\n".join(w))
    texts += [f"{a} {passage}\t{b}" for a, b in itertools.pairwise(base)]
    texts += [None, "", " \n ", "one", "one", "a " * 300, passage, "x" * 5000, base[1] * 40]
    rows = [(i, t, "en", ("b", "a", None)[i % 3], 0, 1.0) for i, t in enumerate(texts)]
    rng.shuffle(rows)
    return rows


@pytest.fixture(scope="module")
def rows():
    return make_docs()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, DOCS).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def test_index_against_brute_force():
    rng = np.random.default_rng(1)
    for _ in range(150):
        least, k, sigma = int(rng.integers(2, 6)), int(rng.integers(1, 9)), int(rng.integers(1, 5))
        segs = [rng.integers(0, sigma, size=rng.integers(1, 16)) for _ in range(k)]
        docs = rng.integers(0, 5, size=k)
        starts = np.cumsum([0] + [len(s) for s in segs])[:-1]
        s, a, b = Index(np.concatenate(segs), starts, docs).smaller_matches(least)
        windows = [{tuple(x[i : i + least]) for i in range(len(x) - least + 1)} for x in segs]
        for i, x in enumerate(segs):
            got, want = np.zeros(len(x), bool), np.zeros(len(x), bool)
            for seg, p, q in zip(s, a, b):
                if seg == i:
                    got[p:q] = True
            for j in range(len(x) - least + 1):
                if any(docs[o] < docs[i] and tuple(x[j : j + least]) in windows[o] for o in range(k)):
                    want[j : j + least] = True
            assert (got == want).all()


@pytest.mark.parametrize("hot", [64, 1])
def test_substring_dedup(docs, none, rows, hot):
    got = {r["doc_id"]: r for r in substring_dedup._with_cuts(docs.select("doc_id", "text"), hot=hot).mapInArrow(substring_dedup._digests, "doc_id long, n_words long, n_removed long, kept_sha256 string").collect()}
    first = {}
    for i, t, *_ in sorted(rows):
        w = words_of(t)
        for j in range(len(w) - 49):
            first.setdefault(tuple(w[j : j + 50]), i)
    for i, t, *_ in rows:
        w = words_of(t)
        gone = {j + k for j in range(len(w) - 49) if first[tuple(w[j : j + 50])] < i for k in range(50)}
        kept = b" ".join(x for j, x in enumerate(w) if j not in gone)
        assert (got[i]["n_words"], got[i]["n_removed"], got[i]["kept_sha256"]) == (len(w), len(gone), hashlib.sha256(kept).hexdigest())


def test_deduplicated_keeps_columns(docs, none):
    out = substring_dedup.deduplicated(docs)
    assert out.columns == docs.columns
    assert out.filter("text LIKE '%x%'").count() >= 1
    assert substring_dedup.deduplicated(none).count() == 0


def test_near_duplicates(docs, none, rows):
    got = {r["doc_id"]: r for r in near_duplicates.near_duplicates(docs, 2, 80).collect()}
    sets = {i: (frozenset(zip(w, w[1:])) if len(w) > 1 else frozenset(w)) for i, t, *_ in rows for w in [words_of((t or "").lower())]}
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= 80 * len(sets[a] | sets[b]):
            x, y = sorted((find(a), find(b)))
            up[y] = x
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == {i: (len(sets[i]), find(i)) for i in sets}
    assert near_duplicates.near_duplicates(none).count() == 0


def test_sketch_fills_and_agrees():
    s = near_duplicates.Sketcher(200)
    rng = np.random.default_rng(2)
    for n in (1, 3, 50, 4000):
        x = rng.integers(0, 1 << 63, n).astype(np.uint64)
        assert (s(x) < np.iinfo(np.uint64).max).all()
    x = rng.integers(0, 1 << 63, 1100).astype(np.uint64)
    assert abs((s(x[:1000]) == s(x[100:])).mean() - 900 / 1100) < 0.12


def test_components(spark):
    edges = [(i, i + 1) for i in range(50)] + [(100, j) for j in range(101, 140)] + [(7, 7)]
    got = {r["v"]: r["component"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(51)} | {j: 100 for j in range(100, 140)}


def test_source_mix(docs, none, rows):
    got = {r["doc_id"]: r for r in source_mix.plan(docs.select("doc_id", "source", "text", "score")).collect()}
    size = {}
    for i, t, _, s, *_ in rows:
        size[s] = size.get(s, 0) + len(words_of(t))
    weight = {"a": 5, "b": 2, None: 1}
    total, full = sum(size.values()), set()
    while True:
        rest = total - sum(3 * size[s] for s in full)
        w = sum(weight[s] for s in size if s not in full)
        over = {s for s in size if s not in full and rest * weight[s] / w > 3 * size[s]}
        if not over:
            break
        full |= over
    target = {s: 3 * size[s] if s in full else rest * weight[s] / w for s in size}
    taken = {}
    for i, t, _, s, *_ in rows:
        r = got[i]
        assert r["size"] == len(words_of(t)) and r["source_size"] == size[s] and abs(r["target"] - target[s]) < 1e-6
        assert 0 <= r["taken"] <= 3 * r["size"]
        taken[s] = taken.get(s, 0) + r["taken"]
    assert all(abs(taken[s] - target[s]) <= 1 for s in size)
    order = source_mix.training_order(docs)
    assert order.columns == [*docs.columns, "_copy", "_position"]
    assert order.agg(F.sum(source_mix.word_count(F.col("text")))).first()[0] == sum(taken.values())
    assert source_mix.plan(none.select("doc_id", "source", "text")).count() == 0


def test_schedule_inverts(spark):
    shape = source_mix.Schedule(((0.0, 0.5), (0.5, 1.0), (1.0, 1.5)))
    at = spark.range(0, 11).select(source_mix._time(F.col("id") / 10, shape).alias("t")).collect()
    area = lambda t: np.trapezoid(np.interp(x := np.linspace(0, t, 2001), *zip(*shape.knots)), x)
    assert all(abs(area(r["t"]) / area(1) - i / 10) < 1e-3 for i, r in enumerate(at))


def test_quality_rules(docs, none, rows):
    led = quality_rules.ledger(docs.select("doc_id", "text", F.lit(1).alias("kept")))
    got = {r["doc_id"]: r for r in led.collect()}
    for i, t, *_ in rows:
        w = words_of(t)
        grams = [tuple(w[j : j + 3]) for j in range(len(w) - 2)]
        again = {j + k for j, g in enumerate(grams) if grams.count(g) > 1 for k in range(3)}
        lines = [x for x in (t or "").split("\n") if words_of(x)]
        assert (got[i]["n_words"], got[i]["n_repeat_words"], got[i]["n_dup_lines"]) == (len(w), len(again), len(lines) - len(set(lines)))
        assert bool(got[i]["fail_bits"] & 3) == (len(w) < 50 or 100 * len(again) > 50 * len(w))
    table = {r["rule"]: r for r in quality_rules.ablations(led).collect()}
    assert table["too_few_words"]["n_failed"] == sum(len(words_of(t)) < 50 for _, t, *_ in rows)
    assert "kept_base-1" in quality_rules.apply_policies(led).columns
    assert quality_rules.ledger(none.select("doc_id", "text")).count() == 0


def test_license_expressions():
    read = lambda x: (license_scan.postfix(x) or (None,))[0]
    e = read("(MIT OR Apache-2.0) AND GPL-2.0-only WITH Classpath-exception-2.0 */")
    assert e == ["mit", "apache-2.0", "or", "gpl-2.0-only with classpath-exception-2.0", "and"]
    assert license_scan.evaluate(e, frozenset({"mit"}))[1] is False
    assert license_scan.evaluate(read("MIT OR GPL-3.0-only"), frozenset({"mit"}))[1] is True
    for bad in ("AND MIT", "(MIT", "", "(MIT OR ISC) WITH x", "MIT WITH (x OR y)", "MIT WITH x WITH y", "MIT WITH", "MIT AND"):
        assert read(bad) is None
    found = license_scan.scan("x; Under the MIT-License, under THE mit license. SPDX-License-Identifier: ISC OR (MIT and GPL-2.0+)", license_scan.automaton())
    assert (found["n_base"], found["first_word"], found["last_word"], found["base_labels"], found["labels"], found["score"]) == (2, 1, 5, "mit", "gpl-2.0+,isc,mit", 1.0)
    assert (found["expressions"], found["permitted"]) == ("isc or (mit and gpl-2.0+)", True)
    assert license_scan.scan(None, license_scan.automaton())["n_words"] == 0


def test_license_tags_that_prove_little():
    scan = lambda t: license_scan.scan(f"SPDX-License-Identifier: {t}", license_scan.automaton())
    assert (scan("see LICENSE file")["labels"], scan("see LICENSE file")["score"]) == ("", 0.0)
    assert (scan("MIT and Foo-1")["labels"], scan("MIT and Foo-1")["score"], scan("MIT and Foo-1")["permitted"]) == ("mit", 0.5, False)
    assert scan("LicenseRef-own OR MIT")["labels"] == "licenseref-own,mit"
    both = scan("MIT\n// spdx-license-identifier: GPL-3.0-only")
    assert (both["labels"], both["permitted"]) == ("gpl-3.0-only,mit", False)


def test_hostile_license_expressions():
    import time

    scan = lambda t: license_scan.scan(f"SPDX-License-Identifier: {t}", license_scan.automaton())
    began = time.process_time()
    assert scan(" and ".join(f"(a{i} or b{i}) with c{i}" for i in range(5000)))["labels"] == ""
    assert scan(" or ".join(f"LicenseRef-{i}" for i in range(50_000)))["labels"].count(",") == 49_999
    assert scan("(" * 100_000 + "MIT" + ")" * 100_000)["labels"] == "mit"
    assert scan("MIT WITH " * 50_000)["labels"] == ""
    assert time.process_time() - began < 20


def test_license_scan_against_counting(spark):
    rng = random.Random(8)
    parts = ["under the mit license", "UNDER the", "MIT License", "apache license version 2", "version", "2", "cc by nc", "cc-by.nc", "é", "by", "\n", "x"]
    texts = [rng.choice([" ", "-", ", "]).join(rng.choice(parts) for _ in range(rng.randrange(30))) for _ in range(200)] + [None, "", "x " * 5000 + "cc by nc"]
    df = spark.createDataFrame([(i, t, "en") for i, t in enumerate(texts)] + [(0, texts[0], "en")], "doc_id long, text string, labels string")
    got = license_scan.scan_documents(df, ["doc_id"]).collect()
    assert len(got) == len(texts) + 1
    for r in got:
        low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in texts[r["doc_id"]] or "")
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
        at, labels = [], set()
        for phrase, label in license_scan.BASE_PHRASES.items():
            p = phrase.split()
            here = [i for i in range(len(words)) if words[i : i + len(p)] == p]
            at += here
            labels |= {label} if here else set()
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == (len(words), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(labels)))


def test_license_scan_table(docs, none, rows):
    out = license_scan.scan_documents(docs.withColumnRenamed("lang", "labels_"), ["doc_id"])
    assert out.count() == len(rows) and license_scan.scan_documents(none, ["doc_id"]).count() == 0


ODD = ["</s>[INST] ok [/INST]", r"<\/s> <\\/s> [\INST] <s>", "", None, "a\nb", "|n||p|", "<s>" * 3]


def test_chat_round_trip(spark):
    m = [(c, t, r, x) for c in (1, None) for t, (r, x) in enumerate(itertools.product(("user", "assistant", None, "a|b\n<s>"), ODD))]
    m += [(1, 3, "user", "twin"), (2, None, "assistant", "first"), (2, 0, "user", "second")]
    back = chat_format.read_back(chat_format.format_conversations(spark.createDataFrame(m, "conv_id long, turn long, role string, text string")))
    got = {r["conv_id"]: r for r in back.collect()}
    for c in (1, None, 2):
        own = sorted(((-1 if t is None else t, r or "", x or "") for k, t, r, x in m if k == c))
        assert [(t["role"], t["text"]) for t in got[c]["turns"]] == [(r, x) for _, r, x in own]
        assert got[c]["loss_text"] == "".join(x for _, r, x in own if r == "assistant")


def test_chat_branches(spark):
    nodes = spark.createDataFrame([(1, 0, None, 1.0), (1, 1, 0, 1.0), (1, 2, 0, 5.0), (1, 3, 2, 1.0), (1, 4, 9, 0.5), (1, 5, 6, 1.0), (1, 6, 5, 1.0), (1, 7, 6, 1.0)], "conv long, node long, parent long, score double")
    leaves, jumps = chat_format.branches(nodes)
    got = {r["node"]: (r["depth"], r["score"]) for r in leaves.collect()}
    assert got == {1: (2, 2.0), 3: (3, 7.0), 4: (1, 0.5)}
    marks = chat_format.path_marks(chat_format.ranked(leaves, 1), jumps).collect()
    assert sorted((r["depth"], r["node"]) for r in marks) == [(1, 0), (2, 2), (3, 3)]


def nearest_by_force(x, ids, q, k=20):
    """(vec_id, score) of the k nearest rows of row q, by products in double precision."""
    s = (x * x[q]).sum(axis=1)
    return [(ids[i], s[i]) for i in np.lexsort((ids, -s)) if ids[i] != ids[q]][:k]


def searched(df, **how):
    got = {}
    for r in nearest.search(df, F.col("vec_id") % 20 == 0, **how).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
        assert r["rank"] == len(got[r["query_id"]])
    return got


def recall_of(got, x, ids):
    """Share of the true neighbours' scores found; what is found has its true score and stands in order."""
    hit = n = 0
    for q in [i for i in range(len(x)) if ids[i] % 20 == 0]:
        want, own = nearest_by_force(x, ids, q), got[ids[q]]
        assert len(own) == len(want) and own == sorted(own, key=lambda r: (-r[1], r[0]))
        hit += len({i for i, _ in own} & {i for i, _ in want})
        n += len(want)
    return hit / n


@pytest.mark.parametrize("length", [1.0, 1e-7, 1e-160, 1e150])
def test_nearest(spark, length):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(1500, 16)) * length
    x[7] = x[8] = x[9]
    odd = [(5000, None, "z"), (5001, [0.0] * 16, "z"), (5020, [float("nan")] * 16, "z"), (5040, [1.0], "z")]
    df = spark.createDataFrame([(i, [float(v) for v in r], "z") for i, r in enumerate(x)] + odd, "vec_id long, embedding array<double>, rank string")
    got = searched(df)
    assert set(got) == set(range(0, 1500, 20))
    if length > 1e-150:  # smaller products are all zero in doubles
        assert recall_of(got, x, np.arange(1500)) >= 0.93


def test_nearest_of_copies(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(300, 16)).astype(np.float32)
    x = np.concatenate([x, np.repeat(x[40:41], 400, axis=0), np.repeat(x[50:51], 15, axis=0)])
    ids = np.concatenate([np.arange(300), np.arange(1000, 1400), np.arange(2000, 2015)])
    rows = [(int(i), [float(v) for v in r]) for i, r in zip(ids, x)]
    df = spark.createDataFrame(rows + rows[:1] * 60 + rows[40:41] * 30, "vec_id long, embedding array<float>")
    got = searched(df)
    assert recall_of(got, x.astype(float), ids) >= 0.95
    assert [i for i, _ in got[1000]] == [40, *range(1001, 1020)] and [i for i, _ in got[40]] == list(range(1000, 1020))


def test_nearest_of_ties_and_unequal_lengths(spark):
    rng = np.random.default_rng(5)
    x = rng.integers(-2, 3, size=(500, 8)).astype(float)
    x[(x == 0).all(axis=1)] = 1
    df = spark.createDataFrame([(i, [int(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<int>")
    got = searched(df, recall=1.0, tune_queries=25)
    assert all(got[q] == nearest_by_force(x, np.arange(500), q) for q in got) and len(got) == 25


def test_nearest_without_rows_or_queries(spark):
    df = spark.createDataFrame([(3, [1.0, 2.0]), (4, [2.0, 1.0])], "vec_id long, embedding array<double>")
    assert searched(df) == {} and searched(df.filter("false")) == {}
    one = df.union(spark.createDataFrame([(20, [1.0, 0.0])], df.schema))
    assert searched(one) == {20: [(4, 2.0), (3, 1.0)]}


def test_nearest_visits_few_rows(spark):
    rng = np.random.default_rng(6)
    x = rng.normal(size=(8000, 32))
    x = np.repeat(x[:400], 20, axis=0) + 0.6 * x  # neighbours among noise
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    rows, dim = nearest.usable(df)
    points = nearest.points_of(rows, 20)
    queries = points.filter("low % 20 = 0")
    hashing = nearest.hashing_for(points, dim)
    least = nearest.tuned(points, queries, hashing, 20, 0.95, 64)
    assert nearest.volume(points, queries, hashing, least) < 0.3
    assert recall_of(searched(df), x, np.arange(8000)) >= 0.93


def test_packing(docs, none, rows):
    packed = packing.pack(docs, packing.public_vocabulary(), with_ids=True).collect()
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.public_vocabulary())
    own, seq = {}, {}
    for r in packed:
        own.setdefault(r["doc_id"], []).append((r["start"], r["length"], r["ids"]))
        seq.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for i, t, *_ in rows:
        ids = b"".join(x for _, _, x in sorted(own[i]))
        assert np.frombuffer(ids, "<u4").tolist() == [*tok.encode(t or "", add_special_tokens=False).ids, 2]
    for parts in seq.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 4096
    assert packing.pack(none, packing.public_vocabulary()).count() == 0


HOSTILE = ["It's they'll 'S ''s don'T x's9", "a<|endoftext|>b <|ENDOFTEXT|> <|x", "İstanbul É\u0301cole \u00d7 3\u00f74 ªº µm ½", "\u00a0\u0085\x1c\x00 a\u00adb", "日本語 텍스트 e\u0301", "A1b22,,..c!!", "x" * 3000, "data:" + "Qk0=" * 2000, "\u200d👩‍👩‍👧 ÀÉÎõü Ǆ ŀ", "", None, "a\n\tb  c", "'", "' s", "\u00c3\u0097", "<", "|>"]


def test_token_ids_of_hostile_texts():
    ids = packing.Ids(packing.public_vocabulary(), 20_000)
    assert ids.by_unit
    rng = random.Random(9)
    signs = "aB'é\u00d7<|>1. \n\u0130\u00a0s日\u0301"
    texts = HOSTILE + ["".join(rng.choice(signs) for _ in range(rng.randrange(40))) for _ in range(3000)] + HOSTILE
    for part in (texts, texts[:1], [None], []):
        got = list(ids(pa.array(part, pa.string())))
        want = [ids.tokenizer.encode(t or "", add_special_tokens=False).ids for t in part]
        assert [np.frombuffer(x, "<u4").tolist() for x in got] == want
    assert ids.units.held < 20_000 + 20_000


def test_other_tokenizers_take_whole_texts(tmp_path):
    from tokenizers import Tokenizer, models, pre_tokenizers

    tok = Tokenizer(models.WordLevel({"a": 0, "b": 1, "?": 2}, unk_token="?"))
    tok.pre_tokenizer = pre_tokenizers.Whitespace()
    tok.save(str(tmp_path / "t.json"))
    ids = packing.Ids(str(tmp_path / "t.json"))
    assert not ids.by_unit and [np.frombuffer(x, "<u4").tolist() for x in ids(pa.array(["a b", None, "c a"]))] == [[0, 1], [], [2, 0]]


def test_pieces():
    for n in (1, 63, 64, 100, 2048, 4096, 4097, 50_000):
        p = list(packing.pieces(n))
        assert sum(a for a, _ in p) == n and all(j == 0 and a < 64 or a * j <= 4096 for a, j in p)


def test_web_archive(spark, tmp_path):
    pages = [(5, "http://b.org/x", "<p>\r\n\r\nhi"), (2, "http://www.a.org:80/?b=2&a=1", "<p>\r\n\r\nhi"), (9, None, None), (8, "not a url\r\n", ""), (None, "http://a.org", "only"), (7, "http://c.org", "é" * 9000)]
    df = spark.createDataFrame([(*p, 1) for p in pages], "page_id long, url string, html string, digest int")
    web_archive.write_archives(df, f"file://{tmp_path}/w")
    got = web_archive.merged_index(web_archive.read_captures(spark, f"file://{tmp_path}/w")).collect()
    by = {r["page_id"]: r for r in got}
    assert len(got) == 6 and by[5]["refers_to"] == 2 and by[9]["refers_to"] == 8 and by[2]["record_type"] == "response"
    assert by[5]["payload_bytes"] == len(b"<p>\r\n\r\nhi") and by[5]["payload_digest"] == by[2]["payload_digest"]
    assert by[2]["url_key"] == "org,a)/?a=1&b=2" and by[7]["payload_bytes"] == 18000
    keys = [(r["url_key"], r["captured"]) for r in got]
    assert keys == sorted(keys)


def test_loser_tree():
    rng = random.Random(4)
    for k in range(1, 9):
        runs = [sorted(rng.randrange(20) for _ in range(rng.randrange(6))) for _ in range(k)]
        assert list(web_archive.loser_tree(runs, lambda x: (x,))) == sorted(itertools.chain(*runs))
    assert list(web_archive.loser_tree([], None)) == []


def test_toxicity(spark):
    rng = random.Random(6)
    text = lambda bad: " ".join(["fool" if bad and rng.random() < 0.2 else rng.choice(["one", "two", "three", "four"]) for _ in range(40)])
    rows = [(i, text(i % 4 == 0), int(i % 4 == 0)) for i in range(600)] + [(1000, None, None), (1001, "", None), (1002, "w " * 20000, None)]
    docs = spark.createDataFrame([(a, b, 0.5) for a, b, _ in rows], "doc_id long, text string, score double")
    labels = spark.createDataFrame([(a, c) for a, _, c in rows], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels)
    got = {r["doc_id"]: r["score"] for r in toxicity.score(docs.drop("score"), model, ["doc_id"]).collect()}
    assert len(got) == 603 and all(0 <= s <= 1 for s in got.values())
    assert all((got[i] >= 0.7) == (i % 4 == 0) for i in range(600))
    assert toxicity.fit(docs, labels.filter("false")).constant == 0.0


def test_features_of_odd_texts():
    texts = [None, "", " ", "A", "!!! you @@", "\u00a0", "\u3000 \u2003", "\x1c\x1d", "\u0130 you"]
    x = toxicity.features(pa.array(texts), toxicity.Weights({}))
    assert x.shape == (len(texts), len(toxicity.FEATURES)) and np.isfinite(x).all()
    assert [len(toxicity.lower_words(t)) for t in texts] == [0, 0, 0, 1, 3, 1, 2, 1, 2]


def test_features_against_counting():
    weights = toxicity.Weights({"foo": 2.0, "bar*": 1.0})
    texts = ["Foo you bars! XYZ f00", "one two three", "you " * 9 + "foo"]
    x = toxicity.features(pa.array(texts), weights)
    name = {n: i for i, n in enumerate(toxicity.FEATURES)}
    assert [len([w for w in toxicity.lower_words(t) if weights([w])[0]]) / len(t.split()) for t in texts] == x[:, name["density"]].tolist()
    assert [sum(c.isupper() for c in t) / sum(c.isalpha() for c in t) for t in texts] == pytest.approx(x[:, name["capitals"]].tolist())
    assert [t.count("!") / len(t) for t in texts] == pytest.approx(x[:, name["exclamation"]].tolist())
    assert x[:, name["heaviest"]].tolist() == [2.0, 0.0, 2.0] and x[:, name["near_second_person"]].tolist() == [1.0, 0.0, 1.0]


def test_trees_and_calibration():
    rng = np.random.default_rng(0)
    x = rng.random((2000, 3))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.3)).astype(float)
    trees = toxicity.boost(x, y)
    assert ((trees.raw(x) > 0) == (y > 0)).mean() > 0.97
    raw = rng.normal(size=300)
    label = (rng.random(300) < 1 / (1 + np.exp(-raw))).astype(float)
    at, level = toxicity.isotonic(raw, label)
    order = np.argsort(raw)
    want = label[order].copy()  # the largest mean from the left that any right end allows
    want = [max(min(want[a : b + 1].mean() for b in range(i, 300)) for a in range(i + 1)) for i in range(0, 300, 25)]
    near = np.abs(at[None, :] - raw[order][::25, None]).argmin(1)
    assert (np.diff(level) >= 0).all() and np.abs(level[near] - want).max() < 0.2


def test_toxicity_of_odd_tables(spark):
    rows = [(0, "\u00a0", 1), (0, "\u00a0", 1), (1, None, None), (None, "\u3000", 2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score int")
    model = toxicity.Model({}, toxicity.boost(np.random.default_rng(1).random((50, len(toxicity.FEATURES))), np.arange(50) % 2.0), (np.array([-1.0, 1.0]), np.array([0.0, 1.0])))
    got = toxicity.score(docs.drop("score"), model, ["doc_id"]).collect()
    assert len(got) == 4 and len({r["score"] for r in got if r["doc_id"] == 0}) == 1
    assert toxicity.score(docs.filter("false"), model, ["doc_id"]).count() == 0


def test_near_duplicates_of_a_group_around_the_threshold(spark):
    rng = random.Random(5)
    base = [f"w{i}" for i in range(120)]
    texts = [[f"m{rng.randrange(400)}" if rng.random() < rate else w for w in base] for rate in (0.02, 0.05, 0.08) for _ in range(30)]
    sets = [{tuple(t[i : i + 2]) for i in range(len(t) - 1)} for t in texts]
    want = list(range(len(texts)))
    for i, x in enumerate(sets):
        for j in range(i):
            if 100 * len(x & sets[j]) >= 80 * len(x | sets[j]):
                a, b = sorted((want[i], want[j]))
                want = [a if w == b else w for w in want]
    assert 1 < len(set(want)) < len(want)
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in near_duplicates.near_duplicates(docs, width=2).collect()}
    assert got == dict(enumerate(want))
