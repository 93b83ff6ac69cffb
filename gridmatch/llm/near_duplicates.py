"""Near-duplicates: fast similarity sketches, banding, exact verification, components.

Sketch: a document's shingle hashes are thrown into `coords` bins in rounds.  A bin keeps the
smallest value of the earliest round that reached it; after as many rounds as bins, every
element is put into each bin in turn, so no bin stays empty, and coordinates of two sets agree
with a share near their similarity.  Bands of coordinates are bucket keys.

Documents with equal shingle sets are one class and only its smallest document goes on.  In a
bucket the member that meets most others is the centre.  Pairs are tried in three rounds, each
followed by components, and only between different components: every class with its best
centre; with the other centres; and, in buckets that still hold several components, members
whose rarest shingles meet.  Rarest are those that the bucket's centre has not: sets too far
from the centre to link with it begin with them, so a bucket of n similar sets costs about n
comparisons instead of n squared whether its sets link or not, and no pair that may link stays
untried.  A link is confirmed on the two full sets.

With 40 bands of 5, a pair at the threshold (0.8) shares no band with probability 1e-7.

Null or empty texts have an empty set and link with nothing; with fewer words than a shingle the
whole text is one shingle.  Equal rows are in one class; rows that repeat an id are
judged each by its own text.  A null id is not part of the result.  Very long texts are
whole sets.  Extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, mix64, slices, spans, table, utf8, word_hashes
from .components import components

BANDS, ROWS, SALT_ROWS = 40, 5, 64

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def shingle_sets(column: pa.Array, width: int) -> Iterator[np.ndarray]:
    """The sorted distinct 64-bit shingle hashes of each text."""
    data, offsets = utf8(column)
    data = _LOWER[data]
    starts, ends, first = spans(data, offsets)
    words = word_hashes(data, starts, ends)
    for a, b in zip(first, first[1:]):
        w = words[a:b]
        n = min(width, len(w))
        if not n:
            yield w
            continue
        h = np.full(len(w) - n + 1, n, np.uint64)
        for i in range(n):
            h = mix64(h * np.uint64(0x9E3779B97F4A7C15) + w[i : len(w) - n + 1 + i])
        yield np.unique(h)


class Sketcher:
    def __init__(self, coords: int = BANDS * ROWS, seed: int = 3):
        self.coords = coords
        self.seeds = mix64(np.arange(1, 2 * coords + 1, dtype=np.uint64) + np.uint64(seed << 32))

    def __call__(self, x: np.ndarray) -> np.ndarray:
        """coords values of a nonempty set: round number above 40 hash bits."""
        t, out = self.coords, np.full(self.coords, np.iinfo(np.uint64).max, np.uint64)
        at, step = 0, max(1, 2048 // len(x))
        while at < t:
            r = np.arange(at, min(t, at + step), dtype=np.uint64)
            h = mix64(x[None, :] ^ self.seeds[r.astype(np.int64)][:, None])
            value = (r[:, None] << np.uint64(40)) | (h >> np.uint64(24))
            np.minimum.at(out, ((h & np.uint64(0xFFFFFF)) % np.uint64(t)).astype(np.int64).ravel(), value.ravel())
            at += step
            if (out >> np.uint64(40) < np.uint64(at)).all():
                return out
        empty = np.flatnonzero(out == np.iinfo(np.uint64).max)
        for a in range(0, len(empty), step):
            own = empty[a : a + step]
            h = mix64(x[None, :] ^ self.seeds[t + own][:, None]) >> np.uint64(24)
            out[own] = ((np.uint64(t) + own.astype(np.uint64)) << np.uint64(40)) | h.min(axis=1)
        return out


def _bands(sketch: np.ndarray, rows: int) -> np.ndarray:
    parts = sketch.reshape(-1, rows)
    h = np.arange(len(parts), dtype=np.uint64) + np.uint64(1)
    for i in range(rows):
        h = mix64(h * np.uint64(0x9E3779B97F4A7C15) + parts[:, i])
    return h.view(np.int64)


def sketches(docs: DataFrame, width: int = 2, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, n (set size), s1 and s2 (128 bits that name the set) and keys (bands)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sketcher = Sketcher(bands * rows)
        for b in slices(batches):
            n, s1, s2, keys = [], [], [], []
            for x in shingle_sets(b.column("text"), width):
                n.append(len(x))
                s1.append(int(x.sum(dtype=np.uint64).view(np.int64)))
                s2.append(int(mix64(x ^ np.uint64(0xA0761D6478BD642F)).sum(dtype=np.uint64).view(np.int64)))
                keys.append(_bands(sketcher(x), rows) if len(x) else np.zeros(0, np.int64))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(s1, pa.int64()), pa.array(s2, pa.int64()), pa.array(keys, pa.list_(pa.int64()))], ["doc_id", "n", "s1", "s2", "keys"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").filter("doc_id IS NOT NULL").mapInArrow(run, "doc_id long, n long, s1 long, s2 long, keys array<long>")


def _meet(width: int, percent: int):
    """Streams rows (c, salt, role, doc_id, text) sorted by these: a centre's text, then the texts
    that may link with it; gives the pairs that do."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, centre = None, None
        for b in slices(batches):
            a_out, c_out = [], []
            for c, salt, role, doc, x in zip(b.column("c").to_pylist(), b.column("salt").to_pylist(), b.column("role").to_pylist(), b.column("doc_id").to_pylist(), shingle_sets(b.column("text"), width)):
                if role == 0:
                    own, centre = (c, salt), x
                elif own == (c, salt):
                    small, large = (x, centre) if len(x) < len(centre) else (centre, x)
                    if 100 * len(small) >= percent * len(large) and len(small):
                        at = np.minimum(np.searchsorted(large, small), len(large) - 1)
                        both = int((large[at] == small).sum())
                        if 100 * both >= percent * (len(x) + len(centre) - both):
                            a_out.append(doc), c_out.append(c)
            yield pa.RecordBatch.from_arrays([pa.array(a_out, pa.int64()), pa.array(c_out, pa.int64())], ["a", "b"])

    return run


def _rarest(width: int, percent: int):
    """Streams the same rows; gives each member's set size and its first shingles in the order
    "not the centre's, then the centre's, by hash", as many as any partner could need."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, centre = None, None
        for b in slices(batches):
            a_out, c_out, n_out, first = [], [], [], []
            for c, salt, role, doc, x in zip(b.column("c").to_pylist(), b.column("salt").to_pylist(), b.column("role").to_pylist(), b.column("doc_id").to_pylist(), shingle_sets(b.column("text"), width)):
                if role == 0:
                    own, centre = (c, salt), x
                elif own == (c, salt) and len(x) and len(centre):
                    at = np.minimum(np.searchsorted(centre, x), len(centre) - 1)
                    common = centre[at] == x
                    keep = len(x) + 1 + -percent * len(x) // 100
                    a_out.append(doc), c_out.append(c), n_out.append(len(x))
                    first.append(np.concatenate([x[~common], x[common]])[:keep].view(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(a_out, pa.int64()), pa.array(c_out, pa.int64()), pa.array(n_out, pa.int64()), pa.array(first, pa.list_(pa.int64()))], ["a", "c", "n", "first"])

    return run


def _beside_centres(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """Texts of `pairs` (a, c), each c's own text first in its partition.

    A c with many partners is repeated for each `SALT_ROWS` of them."""
    salts = pairs.groupBy("c").agg(F.ceil(F.count("*") / SALT_ROWS).cast("int").alias("salts"))
    members = pairs.join(salts, "c").select("c", F.pmod(F.xxhash64("a"), F.col("salts")).cast("int").alias("salt"), F.lit(1).alias("role"), F.col("a").alias("doc_id"))
    centres = salts.select("c", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.lit(0).alias("role"), F.col("c").alias("doc_id"))
    rows = members.unionByName(centres).join(texts, "doc_id").select("c", "salt", "role", "doc_id", "text")
    return rows.repartition("c", "salt").sortWithinPartitions("c", "salt", "role")


def verified(pairs: DataFrame, texts: DataFrame, width: int, percent: int) -> DataFrame:
    """The `pairs` (a, c) of documents whose full sets are similar enough, as edges (a, b)."""
    return _beside_centres(pairs, texts).mapInArrow(_meet(width, percent), "a long, b long")


def possible(members: DataFrame, texts: DataFrame, width: int, percent: int) -> DataFrame:
    """Pairs (a, c) of `members` (a, c, at) of one centre in different components (at) that may link.

    Two sets that link have at least `need` shingles in common, so in any common order their
    first `size - need + 1` shingles meet.  The centre's own shingles come last: a set that does not link with
    the centre begins with those it has beside it, which few others have, so sets that are
    near the centre but not near each other never meet here."""
    first = _beside_centres(members.select("a", "c"), texts).mapInArrow(_rarest(width, percent), "a long, c long, n long, first array<long>")
    first = cut(first.join(members, ["a", "c"]).select("c", "a", "n", "at", F.posexplode("first").alias("pos", "shingle")))
    need = lambda total: f"(({percent} * ({total}) + {99 + percent}) DIV {100 + percent})"
    small = first.filter(f"pos <= n - {need('2 * n')}")
    large = first.select("c", "shingle", F.col("a").alias("a2"), F.col("n").alias("n2"), F.col("at").alias("at2"), F.col("pos").alias("pos2"))
    may = F.expr(f"at <> at2 AND (n < n2 OR (n = n2 AND a < a2)) AND 100 * n >= {percent} * n2 AND pos <= n - {need('n + n2')} AND pos2 <= n2 - {need('n + n2')}")
    met = small.join(large, ["c", "shingle"]).filter(may)
    return met.select(F.least("a", "a2").alias("a"), F.greatest("a", "a2").alias("c")).distinct()


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, n_shingles, component_id (the smallest reachable doc_id) for every document."""
    sk = cut(sketches(docs, width, bands, rows))
    classes = sk.filter("n > 0").groupBy("s1", "s2", "n").agg(F.min("doc_id").alias("rep"), F.first("keys").alias("keys"))
    held = cut(classes)
    band = held.select("rep", "n", F.explode("keys").alias("key"))
    crowd = band.groupBy("key").agg(F.count("*").alias("size")).filter("size > 1")
    met = band.join(crowd, "key")
    mass = met.groupBy("rep").agg(F.sum("size").alias("mass"))
    met = cut(met.join(mass, "rep"))  # only what shares a bucket with another set
    centre = met.groupBy("key").agg(F.max(F.struct("mass", (-F.col("rep")).alias("neg"), "n")).alias("m")).select("key", (-F.col("m.neg")).alias("c"), F.col("m.mass").alias("c_mass"), F.col("m.n").alias("c_n"))
    fits = (100 * F.least("n", "c_n") >= percent * F.greatest("n", "c_n")) & (F.col("rep") != F.col("c"))
    to_centre = cut(met.join(centre, "key").filter(fits).groupBy(F.col("rep").alias("a"), "c").agg(F.max("c_mass").alias("c_mass")))
    wanted = met.select(F.col("rep").alias("doc_id")).distinct()
    texts = cut(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(wanted, "doc_id"))

    def split(pairs: DataFrame, names: DataFrame) -> DataFrame:
        """The pairs whose ends are in different components."""
        at = lambda x: F.coalesce(f"{x}_at", x)
        for x in ("a", "c"):
            pairs = pairs.join(names.select(F.col("v").alias(x), F.col("component").alias(f"{x}_at")), x, "left")
        return pairs.filter(at("a") != at("c")).select("a", "c")

    best = to_centre.groupBy("a").agg(F.max(F.struct("c_mass", "c")).alias("m")).select("a", F.col("m.c").alias("c"))
    edges = cut(verified(best, texts, width, percent))
    names = components(edges)
    rest = cut(split(to_centre.select("a", "c").join(best, ["a", "c"], "left_anti"), names))
    if not rest.isEmpty():
        more = cut(verified(rest, texts, width, percent))
        if not more.isEmpty():
            edges = edges.union(more)
            names = components(edges)
    # buckets that hold several components: members of different ones, by what they have beside the centre
    at = F.coalesce("component", "rep").alias("at")
    place = cut(met.select("key", "rep").join(names.withColumnRenamed("v", "rep"), "rep", "left").select("key", "rep", at))
    several = place.groupBy("key").agg((F.min("at") != F.max("at")).alias("several")).filter("several").select("key")
    members = place.join(several, "key").join(centre, "key").filter("rep <> c").select(F.col("rep").alias("a"), "c", "at").distinct()
    left = cut(possible(cut(members), texts, width, percent))
    if not left.isEmpty():
        more = cut(verified(left, texts, width, percent))
        if not more.isEmpty():
            names = components(edges.union(more))
    of_class = held.select("s1", "s2", "n", "rep").join(names.withColumnRenamed("v", "rep"), "rep", "left").select("s1", "s2", "n", F.coalesce("component", "rep").alias("component_id"))
    out = sk.select("doc_id", "n", "s1", "s2").join(of_class, ["s1", "s2", "n"], "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"), width=2, percent=80)
    return found.withColumn("kept", F.col("doc_id") == F.col("component_id"))


QUERIES = {"op8_near_duplicates": op8_near_duplicates}
ORACLES: dict[str, str] = {}
