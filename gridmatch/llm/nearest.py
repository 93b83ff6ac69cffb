"""Approximate nearest neighbours by cross-polytope hashing.

A table hashes a vector by one or more pseudo-random rotations (sign flips and fast Hadamard
transforms, three times): each gives the signed axis nearest to the vector, and the axes together
name the bucket.  The larger the search, the more axes: buckets hold about `ROWS` rows at any size,
and the last rotation counts only as many coordinates as that needs.  Rows are stored once in each
table; a query probes the buckets whose axes it is near to, meets the rows there, and ranks them
by the exact inner product.  How near is tuned on `tune_queries` queries against brute force, so
recall reaches `recall` whatever the table's size or shape.

Equal vectors are one point with its `k` + 1 smallest ids: no more of them can be among a row's
`k` nearest, as ties go to the smaller id.  So copies are stored, and asked for, once.

Inner products of vectors whose lengths differ are searched as angles after the usual lift
(one more coordinate makes all rows equally long).

A bucket that is larger than `BLOCK` rows is cut into blocks by a hash of the point; a query goes
to every block of its buckets.  A task holds one block at a time and streams the queries past.

Vectors that are null, zero, of another length than most, or hold null or non-finite components
take no part.  Rows equal in id and vector count once, and no row is its own query's neighbour (nor
is another row of its id); exact ties go to the smaller id.  Lengths may be as small or large as
doubles are: products rank as doubles do, unrounded.  Extra columns are ignored; an empty table,
or one without queries, gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, table

TABLES, BLOCK, ROWS = 8, 500, 300
#: More oversized buckets than this are joined by a shuffle instead of a broadcast.
BROADCAST_BUCKETS = 200_000


def hadamard(x: np.ndarray) -> np.ndarray:
    """Orthonormal fast Hadamard transform of each row; the width is a power of two."""
    n, h = x.shape[1], 1
    while h < n:
        y = x.reshape(len(x), -1, 2, h)
        x = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], 2).reshape(len(x), n)
        h *= 2
    return x / np.sqrt(n)


class Hashing:
    """The tables' rotations, and the lift for unequal lengths.

    `scale` is the largest component of all rows, `longest` the largest length after dividing by it."""

    def __init__(self, dim: int, scale: float, longest: float, lift: bool, points: int, tables: int = TABLES, seed: int = 7):
        self.dim, self.scale, self.longest, self.lift = dim, scale, longest, lift
        self.width = 1 << max(1, (dim + lift - 1).bit_length())
        self.axes: list[int] = []  # signed axes of each rotation
        left = max(2.0, points / ROWS)
        while left > 1:
            self.axes.append(min(2 * self.width, 1 << max(1, int(np.ceil(np.log2(left))))))
            left /= self.axes[-1]
        self.buckets = int(np.prod(self.axes))
        # a row's nearest axis of n is about this far out, in standard deviations
        self.weight = [float(np.sqrt(2 * np.log(n))) for n in self.axes]
        self.signs = np.random.default_rng(seed).choice([-1.0, 1.0], size=(tables, len(self.axes), 3, self.width))

    def _turned(self, x: np.ndarray, query: bool) -> Iterator[list[np.ndarray]]:
        """For each table, each rotation's signed coordinates (a row has unit length, so about 1 each)."""
        wide = np.zeros((len(x), self.width))
        if query:
            y = x / np.abs(x).max(axis=1, keepdims=True)
            wide[:, : self.dim] = y / np.linalg.norm(y, axis=1, keepdims=True)
        else:
            wide[:, : self.dim] = x / self.scale / self.longest
            if self.lift:
                wide[:, self.dim] = np.sqrt(np.maximum(1 - (wide[:, : self.dim] ** 2).sum(1), 0))
        for rotations in self.signs:
            parts = []
            for signs, n in zip(rotations, self.axes):
                y = wide
                for s in signs:
                    y = hadamard(y * s)
                y = y[:, : n // 2] * np.sqrt(self.width)
                parts.append(np.concatenate([y, -y], 1))
            yield parts

    def stored(self, x: np.ndarray) -> np.ndarray:
        """tables x rows: the bucket that holds each row."""
        out = []
        for t, parts in enumerate(self._turned(x, False)):
            code = np.full(len(x), t, np.int64)
            for y in parts:
                code = code * y.shape[1] + y.argmax(1)
            out.append(code)
        return np.stack(out)

    def nearness(self, q: np.ndarray, at: np.ndarray, buckets: np.ndarray) -> np.ndarray:
        """The best nearness, over the tables, of query q[at[i]] to the buckets of the i-th row (tables x rows)."""
        best = np.full(len(at), -np.inf)
        for parts, code in zip(self._turned(q, True), buckets):
            total, left = np.zeros(len(at)), code.copy()
            for y, w in zip(parts[::-1], self.weight[::-1]):
                total += w * y[at, left % y.shape[1]]
                left //= y.shape[1]
            best = np.maximum(best, total)
        return best

    def probes(self, q: np.ndarray, least: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """For each table (query rows, buckets) of nearness `least` or more: axis by axis, only what can still reach it."""
        for t, parts in enumerate(self._turned(q, True)):
            weighted = [w * y for w, y in zip(self.weight, parts)]
            rest = np.cumsum([y.max(1) for y in weighted[::-1]], axis=0)[::-1]
            rest = np.concatenate([rest[1:], np.zeros((1, len(q)))])
            row, code, total = np.arange(len(q)), np.full(len(q), t, np.int64), np.zeros(len(q))
            for y, more in zip(weighted, rest):
                reach = total[:, None] + y[row]
                i, axis = np.nonzero(reach + more[row][:, None] >= least)
                row, code, total = row[i], code[i] * y.shape[1] + axis, reach[i, axis]
            yield row, code


def matrix(column: pa.Array) -> np.ndarray:
    """A list column without nulls, all of one length."""
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(n, -1) if n else np.zeros((0, 0))


def usable(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> tuple[DataFrame, int]:
    """vec_id, v (floats as they came, other numbers as doubles) of the rows that take part, and their dimension."""
    v = F.col(vec_col)
    if vectors.select(v).schema[0].dataType.simpleString() != "array<float>":
        v = v.cast("array<double>")
    ok = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).filter(F.col("vec_id").isNotNull() & F.col("v").isNotNull()).filter(ok)
    most = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()
    dim = most[0]["n"] if most else 0
    return rows.filter(F.size("v") == dim).dropDuplicates(["vec_id", "v"]), dim


def _mark(v) -> list:
    """128 bits that stand for a vector in joins of ids."""
    return [F.xxhash64("v").alias("h1"), F.xxhash64(F.lit(1), "v", F.lit(2)).alias("h2")]


def points_of(rows: DataFrame, k: int) -> DataFrame:
    """point, low (its smallest id), v, ids (the k + 1 smallest), h1, h2: one row for each different vector."""
    marked = rows.select("vec_id", "v", *_mark("v"))
    first = F.row_number().over(Window.partitionBy("h1", "h2").orderBy("vec_id")) <= k + 1  # limited before the shuffle, too
    few = marked.withColumn("_few", first).filter("_few").groupBy("h1", "h2").agg(F.first("v").alias("v"), F.array_sort(F.collect_list("vec_id")).alias("ids"))
    return cut(few.withColumn("low", F.get("ids", 0)).withColumn("point", F.monotonically_increasing_id()))


def _best(q_ids: np.ndarray, q: np.ndarray, c_ids: np.ndarray, c_low: np.ndarray, c: np.ndarray, k: int) -> tuple[np.ndarray, ...]:
    """Each query's k best rows by exact product, then `low`: query ids, row ids, lows, products.  A matrix
    product finds those that may be among them; its rounding is allowed for."""
    with np.errstate(over="ignore", invalid="ignore"):
        s = q @ c.T
        if s.shape[1] > k:
            cut_at = -np.partition(-s, k - 1, axis=1)[:, k - 1]
            slack = np.abs(q) @ np.abs(c).max(axis=0) * (4e-16 * q.shape[1]) + 1e-300
            low = np.where(np.isfinite(slack), cut_at - slack, -np.inf)
            rows, cols = np.nonzero(~(s < low[:, None]))
        else:
            rows, cols = (x.ravel() for x in np.indices(s.shape))
        exact = (q[rows] * c[cols]).sum(axis=1)
    order = np.lexsort((c_ids[cols], c_low[cols], -exact, rows))
    rows, cols, exact = rows[order], cols[order], exact[order]
    begins = np.searchsorted(rows, np.arange(len(q)))
    keep = np.arange(len(rows)) - begins[rows] < k
    return q_ids[rows[keep]], c_ids[cols[keep]], c_low[cols[keep]], exact[keep]


PAIRS = "query long, point long, low long, score double"


class Kept:
    """Pairs so far, reduced to k for each query whenever `most` are held."""

    def __init__(self, k: int, most: int = 1 << 20):
        self.k, self.most, self.parts, self.n = k, most, [], 0

    def add(self, part: tuple) -> Iterator[pa.RecordBatch]:
        self.parts.append(part)
        self.n += len(part[0])
        if self.n > self.most:
            self.reduce()
            if self.n > self.most // 2:
                yield from self.flush()

    def reduce(self) -> None:
        q, p, low, s = (np.concatenate(x) for x in zip(*self.parts))
        order = np.lexsort((p, low, -s, q))
        q, p, low, s = q[order], p[order], low[order], s[order]
        new = np.ones(len(q), bool)  # a pair may come from several tables
        new[1:] = (q[1:] != q[:-1]) | (p[1:] != p[:-1])
        q, p, low, s = q[new], p[new], low[new], s[new]
        begins = np.flatnonzero(np.concatenate([[True], q[1:] != q[:-1]]))
        place = np.arange(len(q)) - np.repeat(begins, np.diff(np.append(begins, len(q))))
        keep = place < self.k
        self.parts = [(q[keep], p[keep], low[keep], s[keep])]
        self.n = int(keep.sum())

    def flush(self) -> Iterator[pa.RecordBatch]:
        if self.n:
            self.reduce()
            yield pa.RecordBatch.from_arrays([*map(pa.array, self.parts[0])], ["query", "point", "low", "score"])
        self.parts, self.n = [], 0


def brute_force(points: DataFrame, q_ids: np.ndarray, q: np.ndarray, k: int) -> DataFrame:
    """Exact neighbours of a few given points: one pass over the rows, k pairs a task and query."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = Kept(k)
        for b in batches:
            for a in range(0, b.num_rows, BLOCK):
                part = b.slice(a, BLOCK)
                yield from kept.add(_best(q_ids, q, part.column("point").to_numpy(), part.column("low").to_numpy(), matrix(part.column("v")), k))
        yield from kept.flush()

    return _top(points.select("point", "low", "v").mapInArrow(scan, PAIRS), k)


def _top(pairs: DataFrame, k: int) -> DataFrame:
    """The k best different points of each query: one shuffle by query serves both steps."""
    best = Window.partitionBy("query").orderBy(F.desc("score"), "low", "point")
    one = pairs.repartition("query").dropDuplicates(["query", "point"])
    return one.withColumn("place", F.row_number().over(best)).filter(F.col("place") <= k).select("query", "point", "score")


def tuned(points: DataFrame, queries: DataFrame, hashing: Hashing, k: int, recall: float, tune_queries: int) -> float:
    """The nearness to a bucket that `recall` of the true neighbours of `tune_queries` hash-picked queries reach."""
    few = queries.orderBy(F.xxhash64("point"), "point").limit(tune_queries).collect()
    ids, q = np.array([r["point"] for r in few]), np.array([r["v"] for r in few], float)
    # k + 1 rows for each of those queries come back, whatever the table's size
    true = brute_force(points, ids, q, k + 1).filter("query <> point").join(points.select("point", F.col("v").alias("w")), "point").select("query", "w").collect()
    if not true:
        return -np.inf
    place = {x: i for i, x in enumerate(ids)}
    at = np.array([place[r["query"]] for r in true])
    near = np.sort(hashing.nearness(q, at, hashing.stored(np.array([r["w"] for r in true], float))))
    return float(near[int(np.floor((1 - recall) * len(near)))])


def hashing_for(points: DataFrame, dim: int, tables: int = TABLES) -> Hashing | None:
    """Rotations for a table of points; None if it is empty."""
    most = points.agg(F.max(F.array_max(F.transform("v", lambda x: F.abs(x.cast("double"))))).alias("m"), F.count("*").alias("n")).first()
    if not most["n"]:
        return None
    m = most["m"]
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + (x / F.lit(m)) * (x / F.lit(m))))
    span = points.agg(F.min(norm).alias("a"), F.max(norm).alias("b")).first()
    return Hashing(dim, m, span["b"], span["a"] < 0.999 * span["b"], most["n"], tables)


def _stored_rows(points: DataFrame, hashing: Hashing) -> DataFrame:
    """bucket, point, low, v: every point once in each table."""

    def stored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for a in range(0, b.num_rows, 1000):
                part = b.slice(a, 1000)
                for codes in hashing.stored(matrix(part.column("v"))):
                    yield pa.RecordBatch.from_arrays([pa.array(codes), part.column("point"), part.column("low"), part.column("v")], ["bucket", "point", "low", "v"])

    rows = points.select("point", "low", "v")
    return rows.mapInArrow(stored, f"bucket long, point long, low long, v {rows.schema['v'].dataType.simpleString()}")


def _probe_rows(queries: DataFrame, hashing: Hashing, least: float) -> DataFrame:
    """bucket, point, low, v: every query once for each bucket it probes."""

    def asked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for a in range(0, b.num_rows, 200):
                part = b.slice(a, 200)
                for rows, codes in hashing.probes(matrix(part.column("v")), least):
                    for x in range(0, len(rows), 20_000):
                        at = pa.array(rows[x : x + 20_000])
                        yield pa.RecordBatch.from_arrays([pa.array(codes[x : x + 20_000]), part.column("point").take(at), part.column("low").take(at), part.column("v").take(at)], ["bucket", "point", "low", "v"])

    rows = queries.select("point", "low", "v")
    return rows.mapInArrow(asked, f"bucket long, point long, low long, v {rows.schema['v'].dataType.simpleString()}")


def volume(points: DataFrame, queries: DataFrame, hashing: Hashing, least: float) -> float:
    """Row visits of an average query, as a share of all points: the search's cost against brute force."""
    held = _stored_rows(points, hashing).groupBy("bucket").agg(F.count("*").alias("n"))
    met = _probe_rows(queries, hashing, least).groupBy("bucket").agg(F.count("*").alias("asked")).join(held, "bucket")
    return (met.agg(F.sum(F.col("n") * F.col("asked"))).first()[0] or 0) / points.count() / max(1, queries.count())


def neighbours(points: DataFrame, queries: DataFrame, hashing: Hashing, least: float, k: int) -> DataFrame:
    """query, point, score: the k best points that a query (itself a point) meets."""
    held, probing = _stored_rows(points, hashing), _probe_rows(queries, hashing, least)
    large = cut(held.groupBy("bucket").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks")).filter("blocks > 1"))
    if large.count() <= BROADCAST_BUCKETS:
        large = F.broadcast(large)
    blocks = F.coalesce("blocks", F.lit(1))
    held = held.join(large, "bucket", "left").select("bucket", F.pmod(F.xxhash64("point"), blocks).cast("int").alias("block"), F.lit(0).alias("role"), "point", "low", "v")
    probing = probing.join(large, "bucket", "left").select("bucket", F.explode(F.sequence(F.lit(0), blocks - 1)).alias("block"), F.lit(1).alias("role"), "point", "low", "v")

    def met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept, own, parts, held_rows = Kept(k), None, [], None
        for b in batches:
            key = np.stack([b.column(n).to_numpy().astype(np.int64) for n in ("bucket", "block", "role")], 1)
            edges = [0, *(np.flatnonzero((np.diff(key, axis=0) != 0).any(1)) + 1), b.num_rows]
            for x, y in zip(edges, edges[1:]):
                if x == y:
                    continue
                if tuple(key[x, :2]) != own:
                    own, parts, held_rows = tuple(key[x, :2]), [], None
                part = b.slice(x, y - x)
                if key[x, 2] == 0:
                    parts.append((part.column("point").to_numpy(), part.column("low").to_numpy(), matrix(part.column("v"))))
                    continue
                if not parts:
                    continue
                if held_rows is None:
                    held_rows = [np.concatenate(x) for x in zip(*parts)]
                for a in range(0, part.num_rows, 500):
                    q = part.slice(a, 500)
                    yield from kept.add(_best(q.column("point").to_numpy(), matrix(q.column("v")), *held_rows, k))
        yield from kept.flush()

    keys = ("bucket", "block")
    return _top(held.unionByName(probing).repartition(*keys).sortWithinPartitions(*keys, "role").mapInArrow(met, PAIRS), k)


def search(vectors: DataFrame, is_query, k: int = 20, recall: float = 0.95, tune_queries: int = 64, tables: int = TABLES, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest rows of every row for which `is_query` holds."""
    rows, dim = usable(vectors, id_col, vec_col)
    points = points_of(rows, k)
    hashing = hashing_for(points, dim, tables)
    asked = rows.filter(is_query).select(F.col("vec_id").alias("query_id"), *_mark("v")).join(points.select("h1", "h2", "point"), ["h1", "h2"]).select("query_id", "point")
    asked = cut(asked)
    queries = points.join(asked.select("point").distinct(), "point", "left_semi")
    if hashing is None or asked.isEmpty():
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    found = neighbours(points, queries, hashing, tuned(points, queries, hashing, k, recall, tune_queries), k + 1)
    # points of equal nearness share their places by id: k + 1 ids are enough, one may be the query's own
    named = found.join(points.select("point", "ids"), "point").select("query", "score", F.explode("ids").alias("vec_id"))
    first = Window.partitionBy("query").orderBy(F.desc("score"), "vec_id")
    lists = named.withColumn("place", F.row_number().over(first)).filter(F.col("place") <= k + 1).groupBy("query").agg(F.collect_list(F.struct("score", "vec_id")).alias("near"))
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    each = asked.join(lists, asked["point"] == lists["query"]).select("query_id", F.inline("near")).filter("vec_id <> query_id")
    return each.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op6_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


QUERIES = {"op6_nearest": op6_nearest}
ORACLES: dict[str, str] = {}
