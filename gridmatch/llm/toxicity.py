"""Toxicity: boosted trees over dense text features, with isotonic calibration.

Everything is learned from labels: a lexicon of words and word beginnings that mark toxic
texts, the trees, and the calibration.  Learning reads a bounded sample (`max_rows` labelled
rows, taken by hash); scoring is one narrow pass over whole texts.

Features: lexicon densities and weights, lexicon words near a second-person word, capitals,
punctuation and obfuscation rates, length.  Ids, language and source are never inputs.

A word is a run of characters other than ASCII white space everywhere, so a text of no-break
spaces alone is one word.  Null and empty texts get the score of a text without words.  Null labels are not used; a
document with several labels counts as toxic if one says so; repeated rows are scored alike.
Without labels of both kinds the score is the constant share of toxic rows (0 without labels).
Extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, slices, spans, table, utf8

#: Second-person words in the corpus' languages, and characters that stand for letters.
SECOND_PERSON = frozenset(b"you your yours yourself u ya tu te toi ton ta tes vous votre vos du dich dir dein deine deinen ihr euch euer sie ti tus tuyo usted ustedes vosotros".split())
LEET = str.maketrans("0134578@$!", "oieastbasi")
EDGE = ".,;:!?\"'()[]{}<>#*$%&|-_~`/\\"

FEATURES = ("density", "hits", "weight", "heaviest", "distinct", "near_second_person", "second_person", "capitals", "shouted", "punctuation", "exclamation", "obfuscated", "length")


def lower_words(text: str | None) -> list[bytes]:
    """The words `spans` counts, in lower case."""
    return (text or "").lower().encode().split()


def terms_of(word: str) -> tuple[str, ...]:
    """What of a lower-case word may be in the lexicon: the bare word, its letters read plainly, and its beginnings."""
    bare = word.strip(EDGE)
    plain = bare.translate(LEET)
    return (bare, *((plain,) if plain != bare else ()), *(plain[:n] + "*" for n in (4, 5) if len(plain) > n))


class Weights:
    """Lexicon weight of a word, remembered for words seen before (a bounded number of bytes)."""

    def __init__(self, lexicon: dict[str, float]):
        self.lexicon, self.seen, self.held = lexicon, {}, 0

    def __call__(self, words: list[bytes]) -> list[float]:
        seen = self.seen
        try:
            return [seen[w] for w in words]
        except KeyError:
            if self.held > 32 << 20:
                seen.clear()
                self.held = 0
            get = self.lexicon.get
            for w in set(words).difference(seen):
                seen[w] = max(get(x, 0.0) for x in terms_of(w.decode()))
                self.held += len(w) + 100
            return [seen[w] for w in words]


_LETTER, _UPPER, _MARK, _SHOUT, _ODD = (np.zeros(256, np.int8) for _ in range(5))
_UPPER[65:91] = 1
_LETTER[65:91] = _LETTER[97:123] = 1
_LETTER[128:] = 1
_MARK[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = 1
_SHOUT[33] = 1
_ODD[[*range(48, 58), *map(ord, "@$*#")]] = 1


def features(column: pa.Array, weights: Weights) -> np.ndarray:
    """One row of FEATURES for each text."""
    data, offsets = utf8(column)
    starts, ends, first = spans(data, offsets)
    run = lambda kind: np.concatenate([np.zeros(1, np.int32), np.cumsum(kind[data], dtype=np.int32)])
    letter, upper, mark, shout, odd = map(run, (_LETTER, _UPPER, _MARK, _SHOUT, _ODD))
    of_text = lambda c: np.diff(c[offsets])
    of_word = lambda flag: np.diff(np.concatenate([[0], np.cumsum(flag)])[first])
    size = ends - starts
    shouted = of_word((upper[ends] - upper[starts] == size) & (size >= 3))
    letters = letter[ends] - letter[starts]
    # an odd character with letters on both sides of the word's middle part
    inner = odd[np.maximum(ends - 1, starts)] - odd[np.minimum(starts + 1, ends)]
    obfuscated = of_word((inner > 0) & (letters >= 2) & (size <= 24))
    n, chars = np.diff(first), np.maximum(np.diff(offsets), 1)
    out = np.zeros((len(column), len(FEATURES)))
    words_n = np.maximum(n, 1)
    for i, text in enumerate(column.to_pylist()):
        if not n[i]:
            continue
        words = lower_words(text)
        w = weights(words)
        at = [j for j, x in enumerate(w) if x]
        if at:
            out[i, 0], out[i, 1] = len(at) / words_n[i], math.log1p(len(at))
            out[i, 2], out[i, 3] = math.log1p(sum(w[j] for j in at)), max(w[j] for j in at)
            out[i, 4] = math.log1p(len({words[j] for j in at}))
            out[i, 5] = sum(not SECOND_PERSON.isdisjoint(words[max(0, j - 6) : j + 7]) for j in at) / len(at)
        out[i, 6] = len(SECOND_PERSON.intersection(words)) / math.log1p(len(words))
    out[:, 7] = of_text(upper) / np.maximum(of_text(letter), 1)
    out[:, 8], out[:, 9], out[:, 10] = shouted / words_n, of_text(mark) / chars, of_text(shout) / chars
    out[:, 11], out[:, 12] = obfuscated / words_n, np.log1p(n)
    return out


@dataclass
class Boosted:
    """Complete trees of `depth` levels as arrays: trees x inner nodes, trees x leaves."""

    start: float
    depth: int = 3
    feature: list = field(default_factory=list)
    cut: list = field(default_factory=list)
    leaf: list = field(default_factory=list)

    def raw(self, x: np.ndarray) -> np.ndarray:
        out, rows = np.full(len(x), self.start), np.arange(len(x))
        for f, c, v in zip(self.feature, self.cut, self.leaf):
            node = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                node = 2 * node + 1 + (x[rows, f[node]] > c[node])
            out += v[node - len(f)]
        return out


def boost(x: np.ndarray, y: np.ndarray, rounds: int = 60, depth: int = 3, rate: float = 0.2, bins: int = 64, least: int = 10) -> Boosted:
    """Second-order boosting of the logistic loss on binned features."""
    edges = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) for c in x.T]
    code = np.stack([np.searchsorted(e, c, side="left") for e, c in zip(edges, x.T)], 1)
    mean = np.clip(y.mean(), 1e-4, 1 - 1e-4)
    model = Boosted(float(np.log(mean / (1 - mean))), depth)
    raw, inner = np.full(len(y), model.start), 2**depth - 1
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-raw))
        g, h = y - p, np.maximum(p * (1 - p), 1e-6)
        node = np.zeros(len(y), np.int64)
        f_at, c_at, k_at = np.zeros(inner, np.int64), np.full(inner, np.inf), np.full(inner, bins + 1)
        for level in range(depth):
            base, width = 2**level - 1, 2**level
            gain_best = np.full(width, 1e-9)
            for f in range(x.shape[1]):
                key = (node - base) * (bins + 1) + code[:, f]
                sums = [np.bincount(key, v, width * (bins + 1)).reshape(width, -1).cumsum(1) for v in (g, h, np.ones(len(y)))]
                (gl, hl, nl), (gt, ht, nt) = sums, [s[:, -1:] for s in sums]
                gain = np.where((nl >= least) & (nt - nl >= least), gl**2 / (hl + 1) + (gt - gl) ** 2 / (ht - hl + 1) - gt**2 / (ht + 1), -1)[:, : len(edges[f])]
                if gain.shape[1]:
                    k = gain.argmax(1)
                    for i in np.flatnonzero(gain[np.arange(width), k] > gain_best):
                        gain_best[i], f_at[base + i], k_at[base + i], c_at[base + i] = gain[i, k[i]], f, k[i], edges[f][k[i]]
            node = 2 * node + 1 + (code[np.arange(len(y)), f_at[node]] > k_at[node])
        leaf = node - inner
        value = rate * np.bincount(leaf, g, inner + 1) / (np.bincount(leaf, h, inner + 1) + 1)
        model.feature.append(f_at), model.cut.append(c_at), model.leaf.append(value)
        raw += value[leaf]
    return model


def isotonic(raw: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators: block centres and their (nondecreasing) means."""
    order = np.argsort(raw, kind="stable")
    blocks: list[list[float]] = []  # sum of raw, sum of y, count
    for r, v in zip(raw[order], y[order]):
        blocks.append([r, v, 1])
        while len(blocks) > 1 and blocks[-2][1] * blocks[-1][2] >= blocks[-1][1] * blocks[-2][2]:
            last = blocks.pop()
            blocks[-1] = [a + b for a, b in zip(blocks[-1], last)]
    return np.array([b[0] / b[2] for b in blocks]), np.array([b[1] / b[2] for b in blocks])


@dataclass
class Model:
    lexicon: dict[str, float]
    trees: Boosted | None
    knots: tuple[np.ndarray, np.ndarray]
    constant: float = 0.0

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.trees is None:
            return np.full(len(x), self.constant)
        raw = self.trees.raw(x)
        # the raw probability keeps order inside a calibrated step
        return np.clip(0.98 * np.interp(raw, *self.knots) + 0.02 / (1 + np.exp(-raw)), 0, 1)


def bucket(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 3


def _count_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    tally: dict[str, Counter] = {"tox": Counter(), "non": Counter()}

    def flush() -> pa.RecordBatch:
        terms = list({*tally["tox"], *tally["non"]})
        out = pa.RecordBatch.from_pydict({"term": pa.array(terms, pa.string()), "tox": pa.array([tally["tox"][t] for t in terms], pa.int64()), "non": pa.array([tally["non"][t] for t in terms], pa.int64())})
        tally["tox"].clear(), tally["non"].clear()
        return out

    for batch in slices(batches):
        for text, toxic in zip(batch.column("text").to_pylist(), batch.column("toxic").to_pylist()):
            tally["tox" if toxic else "non"].update({t for w in set(lower_words(text)) for t in terms_of(w.decode()) if t})
        if len(tally["non"]) > 300_000:
            yield flush()
    yield flush()


def fit(docs: DataFrame, labels: DataFrame, max_rows: int = 12_000, max_terms: int = 400) -> Model:
    """Learn from at most `max_rows` labelled documents whose id is not in the held-out third.

    Three quarters (by hash) teach lexicon and trees, the rest the calibration."""
    spark = docs.sparkSession
    known = labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & (bucket(F.col("doc_id")) != 1))
    known = known.groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = known.withColumn("h", F.xxhash64("doc_id", F.lit(11))).orderBy("h", "doc_id").limit(max_rows)
    # `chosen` has `max_rows` short rows at most, whatever the input
    sample = cut(docs.select("doc_id", "text").join(F.broadcast(chosen.select("doc_id", "toxic", (F.pmod("h", F.lit(4)) == 3).alias("later"))), "doc_id"))
    counts = {r["toxic"]: r["n"] for r in sample.filter("NOT later").groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    n_tox, n_non = counts.get(1, 0), counts.get(0, 0)
    if not n_tox or not n_non:
        return Model({}, None, (np.zeros(1), np.zeros(1)), 1.0 if n_tox else 0.0)
    odds = F.log((F.col("tox") + 0.5) / (n_tox + 1)) - F.log((F.col("non") + 0.5) / (n_non + 1))
    found = (
        sample.filter("NOT later").select("text", "toxic").mapInArrow(_count_terms, "term string, tox long, non long")
        .groupBy("term").agg(F.sum("tox").alias("tox"), F.sum("non").alias("non"))
        .withColumn("odds", odds).filter((F.col("tox") >= max(3, n_tox // 200)) & (F.col("odds") >= 2.5))
        .orderBy(F.desc(F.col("odds") * F.log1p("tox")), "term").limit(max_terms).collect()
    )
    lexicon = {r["term"]: float(r["odds"]) for r in found}

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights = Weights(lexicon)
        for b in slices(batches):
            x = features(b.column("text"), weights)
            yield pa.RecordBatch.from_arrays([pa.array(list(x), pa.list_(pa.float64())), b.column("toxic"), b.column("later")], ["x", "toxic", "later"])

    got = sample.select("text", "toxic", "later").mapInArrow(rows, "x array<double>, toxic int, later boolean").toPandas()
    x, y, later = np.array(got["x"].tolist()), got["toxic"].to_numpy(float), got["later"].to_numpy(bool)
    order = np.lexsort((*x.T, y))  # the same sums whatever order the rows came in
    x, y, later = x[order], y[order], later[order]
    trees = boost(x[~later], y[~later])
    held = later if later.any() and 0 < y[later].mean() < 1 else ~later
    return Model(lexicon, trees, isotonic(trees.raw(x[held]), y[held]))


def score(docs: DataFrame, model: Model, keep: list[str], text: str = "text") -> DataFrame:
    """`keep` columns and `score`, for every row."""
    schema = docs.select(*keep).schema.add("score", "double")
    at = keep.index(text) if text in keep else len(keep)  # the text crosses once

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights = Weights(model.lexicon)
        for b in slices(batches, at):
            s = model.score(features(b.column(at), weights))
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(keep))), pa.array(s)], [*keep, "score"])

    rows_in = docs.select(*keep) if text in keep else docs.select(*keep, F.col(text).alias("_text"))
    return rows_in.mapInArrow(rows, schema)


THRESHOLD = 0.7


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic"))
    return score(docs, model, ["doc_id"]).select("doc_id", F.coalesce(bucket(F.col("doc_id")) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


QUERIES = {"op10_toxicity": op10_toxicity}
ORACLES: dict[str, str] = {}
