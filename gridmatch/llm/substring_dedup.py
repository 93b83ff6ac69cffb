"""Removal of passages that repeat across documents, exact on word windows.

Windows of `window` words are routed by content: a window's anchor is the smallest hash among
its word grams, so equal windows have equal anchors, wherever they stand.  Neighbouring windows
with one anchor are a segment.  The steps:

1. every text gives its segments (anchor, digest, place): about one row for 18 words, no text;
2. segments are counted by anchor and digest; what meets no other document goes away, and of
   equal segments only the smallest document's is searched (the others are removed as copies);
3. the segments left are shards of a compressed full-text index (wavelet matrix, fm_index.py);
   the shard's segments are streamed through it, and the stretches above the window's length
   that occur in a smaller document are reported;
4. an anchor with more than `HOT` different segments (a passage in very many contexts) would be
   one large shard, so its segments are cut again by anchors of longer grams and go through
   2 and 3 as shorter segments; where that does not spread them either (the passage's edges),
   windows meet by their digest;
5. the reported stretches join the texts, whose words they cover go.

Everything is judged on the input.  Null texts have no words; a null doc_id removes nothing and
loses nothing; rows that repeat an id never remove from each other, and each keeps its own
places.  A text shorter than the window is kept whole.  Very long texts are many segments.  An
empty table gives an empty result; extra columns stay in `deduplicated`.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, mix64, slices, span_hashes, spans, table, utf8, word_hashes
from .fm_index import Index

WINDOW, GRAM, HOT, SHARD_WORDS = 50, 16, 64, 400_000


def segments(words: np.ndarray, first: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, ...]:
    """(text, start, windows, anchor, digest) of all segments; start counts words of the batch."""
    empty = (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),) * 2
    if len(words) < window:
        return empty
    at = np.arange(len(words) - gram + 1)
    low = span_hashes(words, at, at + gram, base=0xD1342543DE82EF95)
    width, have = window - gram + 1, 1
    while have < width:  # minima over 1, 2, 4, ... grams, the last step overlapping
        step = min(have, width - have)
        low = np.minimum(low[: len(low) - step], low[step:])
        have += step
    text = np.repeat(np.arange(len(first) - 1), np.diff(first))[: len(low)]
    valid = np.arange(len(low)) + window <= first[text + 1]
    pos = np.flatnonzero(valid)
    if not len(pos):
        return empty
    t, a = text[pos], low[pos]
    new = np.concatenate([[True], (t[1:] != t[:-1]) | (a[1:] != a[:-1])])
    begin = np.flatnonzero(new)
    n = np.diff(np.append(begin, len(pos)))
    start = pos[begin]
    return t[begin], start, n, a[begin], span_hashes(words, start, start + n + window - 1)


def _located(docs: DataFrame, window: int, gram: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            data, offsets = utf8(b.column("text"))
            starts, ends, first = spans(data, offsets)
            t, s, n, anchor, digest = segments(word_hashes(data, starts, ends), first, window, gram)
            at = pa.array(t)
            yield pa.RecordBatch.from_arrays([pa.array(anchor.view(np.int64)), pa.array(digest.view(np.int64)), b.column("doc_id").take(at), b.column("th").take(at), pa.array((s - first[t]).astype(np.int32)), pa.array(n.astype(np.int32))], ["anchor", "digest", "doc_id", "th", "start", "n"])

    return docs.mapInArrow(run, "anchor long, digest long, doc_id long, th long, start int, n int")


def _contents(window: int, gram: int | None):
    """Rows (doc_id, th, text, segs) to the segments' words; where the anchor is hot, to shorter
    segments by anchors of `gram` words, or to windows if there is none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            data, offsets = utf8(b.column("text"))
            starts, ends, first = spans(data, offsets)
            words = word_hashes(data, starts, ends)
            cols: list[list] = [[] for _ in range(8)]
            for doc, th, x, segs in zip(b.column("doc_id").to_pylist(), b.column("th").to_pylist(), first, b.column("segs").to_pylist()):
                for g in segs:
                    n = g["n"]
                    own = words[x + g["start"] : x + g["start"] + n + window - 1]
                    if not g["hot"]:
                        new = ([g["anchor"]], [0], [doc], [th], [g["start"]], [n], [g["ask"]], [own.tobytes()])
                    else:
                        if gram:
                            _, s, k, anchor, digest = segments(own, np.array([0, len(own)]), window, gram)
                        else:
                            s, k = np.arange(n), np.ones(n, np.int64)
                            anchor = digest = mix64(span_hashes(own, s, s + window, base=0xA24BAED4963EE407))
                        m = len(s)
                        new = (anchor.view(np.int64).tolist(), digest.view(np.int64).tolist(), [doc] * m, [th] * m, (s + g["start"]).tolist(), k.tolist(), [True] * m, [None] * m)
                    for c, v in zip(cols, new):
                        c.extend(v)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.bool_(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], CONTENT_NAMES)

    return run


CONTENT_NAMES = ["anchor", "digest", "doc_id", "th", "start", "n", "ask", "words"]


def _searched(window: int, shard_words: int):
    """Rows sorted by anchor: whole anchors make shards of about `shard_words`; each is indexed and searched."""

    def shard(rows: list[tuple]) -> pa.RecordBatch:
        parts = [np.frombuffer(r[4], np.int64) for r in rows]
        # anchors keep apart: a shard's matches inside another anchor's segment are true matches too
        starts = np.cumsum([0, *map(len, parts)])[:-1]
        s, a, b = Index(np.concatenate(parts), starts, np.array([r[1] for r in rows])).smaller_matches(window, np.array([r[5] for r in rows]))
        at = np.array([r[3] for r in rows], np.int64)[s]
        return pa.RecordBatch.from_arrays([pa.array([rows[i][1] for i in s], pa.int64()), pa.array([rows[i][2] for i in s], pa.int64()), pa.array((at + a).astype(np.int32)), pa.array((at + b).astype(np.int32))], ["doc_id", "th", "a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        held = 0
        for b in batches:
            for row in zip(*(b.column(n).to_pylist() for n in ("anchor", "doc_id", "th", "start", "words", "ask"))):
                if held >= shard_words and rows[-1][0] != row[0]:
                    yield shard(rows)
                    rows, held = [], 0
                rows.append(row)
                held += len(row[4]) // 8
        if rows:
            yield shard(rows)

    return run





def _resolved(found: DataFrame, known: DataFrame, window: int, grams: tuple[int, ...], hot: int, shard_words: int) -> DataFrame:
    """The ranges to remove among the segments `found`; `grams` are those of the cuts left for hot anchors."""
    kinds = found.groupBy("anchor", "digest").agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high"))
    anchors = kinds.groupBy("anchor").agg(F.count("*").alias("kinds"), F.min("low").alias("l"), F.max("high").alias("h")).filter("l < h")
    shared = kinds.join(anchors, "anchor").filter("kinds > 1 OR low < high").select("anchor", "digest", "low", "kinds", "l")
    met = cut(found.join(shared, ["anchor", "digest"]).filter("doc_id > low OR kinds > 1"))
    end = (F.col("start") + F.col("n") + window - 1).alias("b")
    out = met.filter("doc_id > low").select("doc_id", "th", F.col("start").alias("a"), end)
    # the anchor's smallest document is indexed, but has nothing smaller to be searched for
    seg = F.struct("anchor", "start", "n", (F.col("kinds") > hot).alias("hot"), (F.col("doc_id") > F.col("l")).alias("ask"))
    asked = met.filter("doc_id = low AND kinds > 1").groupBy("doc_id", "th").agg(F.collect_list(seg).alias("segs"))
    gram = grams[0] if grams else None
    contents = cut(known.join(asked, ["doc_id", "th"]).select("doc_id", "th", "text", "segs").mapInArrow(_contents(window, gram), "anchor long, digest long, doc_id long, th long, start int, n int, ask boolean, words binary"))
    cold = contents.filter("words IS NOT NULL").repartition("anchor").sortWithinPartitions("anchor")
    out = out.union(cold.select("anchor", "doc_id", "th", "start", "words", "ask").mapInArrow(_searched(window, shard_words), "doc_id long, th long, a int, b int"))
    rest = contents.filter("words IS NULL").select("anchor", "digest", "doc_id", "th", "start", "n")
    if gram and not rest.isEmpty():
        return out.union(_resolved(rest, known, window, grams[1:], hot, shard_words))
    # windows: equal digests are equal windows, so the smallest document of each is the answer
    least = rest.groupBy("digest").agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high")).filter("low < high").select("digest", "low")
    return out.union(rest.join(least, "digest").filter("doc_id > low").select("doc_id", "th", F.col("start").alias("a"), (F.col("start") + window).alias("b")))


def removals(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, hot: int = HOT, shard_words: int = SHARD_WORDS) -> DataFrame:
    """doc_id, th (text hash) and cuts (a, b): the word ranges to remove from each document.
    `docs` has doc_id, text and th."""
    known = docs.filter("doc_id IS NOT NULL AND text IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), "text", "th")
    found = cut(_located(known, window, gram))
    finer = ((window + gram) // 2 + 1, window - 4)  # grams of the cuts for hot anchors
    ranges = _resolved(found, known, window, tuple(g for g in finer if gram < g < window), hot, shard_words)
    return ranges.groupBy("doc_id", "th").agg(F.collect_list(F.struct("a", "b")).alias("cuts"))


def _with_cuts(docs: DataFrame, **how) -> DataFrame:
    docs = docs.withColumn("th", F.xxhash64("text"))
    cuts = removals(docs.select("doc_id", "text", "th"), **how)
    return docs.join(cuts, (docs["doc_id"].cast("long") == cuts["doc_id"]) & (docs["th"] == cuts["th"]), "left").select(*[docs[c] for c in docs.columns if c != "th"], cuts["cuts"])


def _gone(n: int, cuts: list | None) -> np.ndarray:
    turn = np.zeros(n + 1, np.int64)
    for c in cuts or ():
        turn[c["a"]] += 1
        turn[c["b"]] -= 1
    return np.cumsum(turn[:-1]) > 0


def _digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in slices(batches):
        n, gone_n, sha = [], [], []
        for text, cuts in zip(b.column("text").to_pylist(), b.column("cuts").to_pylist()):
            words = (text or "").encode("utf-8", "surrogatepass").split()
            gone = 0
            n.append(len(words))
            if cuts:
                mask = _gone(len(words), cuts)
                gone = int(mask.sum())
                words = [w for w, g in zip(words, mask.tolist()) if not g]
            gone_n.append(gone)
            sha.append(hashlib.sha256(b" ".join(words)).hexdigest())
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(gone_n, pa.int64()), pa.array(sha, pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"])


def deduplicated(docs: DataFrame, **how) -> DataFrame:
    """`docs` with the repeated passages cut out of `text` (white space between kept words stays);
    documents that had words and lost all of them go."""
    marked = _with_cuts(docs, **how)
    names = docs.columns
    i = names.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            texts, keep = [], []
            for text, cuts in zip(b.column("text").to_pylist(), b.column("cuts").to_pylist()):
                keep.append(True)
                if cuts:
                    raw = text.encode("utf-8", "surrogatepass")
                    s, e, _ = spans(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))
                    mask = _gone(len(s), cuts)
                    step = np.flatnonzero(np.diff(np.concatenate([[1], mask, [1]])))
                    text = "".join(raw[s[x] : s[y] if y < len(s) else len(raw)].decode("utf-8", "surrogatepass") for x, y in zip(step[::2], step[1::2]))
                    keep[-1] = not mask.all()
                texts.append(text)
            cols = [b.column(j) if j != i else pa.array(texts, pa.string()) for j in range(len(names))]
            yield pa.RecordBatch.from_arrays(cols, names).filter(pa.array(keep, pa.bool_()))

    return marked.mapInArrow(run, docs.schema)


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return _with_cuts(docs).mapInArrow(_digests, "doc_id long, n_words long, n_removed long, kept_sha256 string")


ORACLE = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') w FROM documents),
s AS (SELECT doc_id, unnest(range(1, len(w) - 48)) p, w FROM d WHERE len(w) >= 50),
g AS (SELECT doc_id, p, md5(array_to_string(w[p:p + 49], ' ')) h FROM s),
f AS (SELECT h, min(doc_id) low FROM g GROUP BY h HAVING count(*) > 1),
b AS (SELECT DISTINCT g.doc_id, g.p + k.k i FROM g JOIN f ON g.h = f.h AND g.doc_id > f.low, (SELECT unnest(range(0, 50)) k) k),
r AS (SELECT doc_id, list(i) gone, CAST(count(*) AS BIGINT) n FROM b GROUP BY doc_id),
x AS (SELECT d.doc_id, unnest(range(1, len(w) + 1)) i, unnest(w) word FROM d),
kept AS (SELECT x.doc_id, string_agg(word, ' ' ORDER BY x.i) t FROM x LEFT JOIN b ON b.doc_id = x.doc_id AND b.i = x.i WHERE b.i IS NULL GROUP BY x.doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) n_words, coalesce(r.n, 0) n_removed, sha256(coalesce(kept.t, '')) kept_sha256
FROM d LEFT JOIN r ON r.doc_id = d.doc_id LEFT JOIN kept ON kept.doc_id = d.doc_id
"""

QUERIES = {"op2_substring_dedup": op2_substring_dedup}
ORACLES = {"op2_substring_dedup": ORACLE}
