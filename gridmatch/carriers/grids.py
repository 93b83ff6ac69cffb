"""The given tables laid out as tiled images: image_id, r, c, bg and features f0, f1, ...

`bg` is a tile's distance to the all-zero background.  Each carrier is one partial-final
aggregation of its table; a dense carrier adds the cells without rows as all-zero tiles.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..features import descriptors as D
from ..tables import load

YEAR0, ROWS, COLUMNS = 1995, 7, 12


def feature_columns(tiles: DataFrame) -> list[str]:
    names = [c for c in tiles.columns if c[0] == "f" and c[1:].isdigit()]
    return sorted(names, key=lambda c: int(c[1:]))


def _with_bg(df: DataFrame, features: dict[str, Column], keys: dict[str, Column]) -> DataFrame:
    out = df.select(*[v.alias(k) for k, v in keys.items()], *[v.cast("long").alias(k) for k, v in features.items()])
    return out.withColumn("bg", sum(F.abs(F.col(k)) for k in features))


def dense(tiles: DataFrame, rows: int, columns: int) -> DataFrame:
    """Every cell of a rows x columns grid for each image; cells without a row are zero."""
    cells = tiles.select("image_id").distinct().withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(rows * columns - 1))))
    cells = cells.select("image_id", F.expr(f"CAST(i DIV {columns} AS INT)").alias("r"), (F.col("i") % columns).cast("int").alias("c"))
    rest = [c for c in tiles.columns if c not in ("image_id", "r", "c")]
    return cells.join(tiles, ["image_id", "r", "c"], "left").select("image_id", "r", "c", *[F.coalesce(x, F.lit(0)).alias(x) for x in rest])


def calendar(spark: SparkSession, sf_dir: str, fill: bool = True) -> DataFrame:
    """C1: suppliers as year x month grids of six line-item features."""
    li = load(spark, sf_dir, "lineitem", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag")
    g = li.groupBy(F.col("l_suppkey").alias("image_id"), (F.year("l_shipdate") - YEAR0).alias("r"), (F.month("l_shipdate") - 1).alias("c")).agg(
        F.count("*").alias("n"),
        F.sum("l_quantity").cast("long").alias("q"),
        F.sum(F.floor(F.col("l_extendedprice") / 1000)).alias("p"),
        F.sum(F.round(F.col("l_discount") * 100).cast("long")).alias("d"),
        F.sum(F.round(F.col("l_tax") * 100).cast("long")).alias("t"),
        F.sum((F.col("l_returnflag") == "R").cast("long")).alias("a"),
    )
    f = {"f0": F.col("n") * 10, "f1": F.expr("q DIV 2"), "f2": F.expr("p DIV 5"), "f3": F.col("d") * 2, "f4": F.col("t") * 2, "f5": F.col("a") * 10}
    tiles = _with_bg(g, f, {k: F.col(k) for k in ("image_id", "r", "c")})
    return dense(tiles, ROWS, COLUMNS) if fill else tiles


PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
STATUSES = ("F", "O", "P")


def order_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C2: nations as year x month grids of order counts by priority and status."""
    o = load(spark, sf_dir, "orders", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")
    n = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    first = F.lit(YEAR0)
    hit = lambda col, v: F.sum((F.col(col) == v).cast("long"))
    g = o.join(n, o.o_custkey == n.c_custkey).groupBy(F.col("c_nationkey").cast("long").alias("image_id"), (F.year("o_orderdate") - first).alias("r"), (F.month("o_orderdate") - 1).alias("c"))
    g = g.agg(*[hit("o_orderpriority", p).alias(f"p{i}") for i, p in enumerate(PRIORITIES)], *[hit("o_orderstatus", s).alias(f"s{i}") for i, s in enumerate(STATUSES)], F.sum(F.floor(F.col("o_totalprice") / 1000)).alias("total"))
    f = {f"f{i}": F.col(f"p{i}") for i in range(5)} | {f"f{5 + i}": F.col(f"s{i}") for i in range(3)} | {"f8": F.col("total")}
    return _with_bg(g, f, {k: F.col(k) for k in ("image_id", "r", "c")})


EVENT_TYPES = ("signup", "view", "error", "click", "purchase")


def activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C3: users as day x quarter-day grids of event counts."""
    e = load(spark, sf_dir, "events", "ts", "user_id", "event_type", "value")
    g = e.groupBy(F.col("user_id").alias("image_id"), (F.dayofmonth("ts") - 1).alias("r"), F.expr("CAST(hour(ts) DIV 4 AS INT)").alias("c"))
    g = g.agg(*[F.sum((F.col("event_type") == t).cast("long")).alias(f"e{i}") for i, t in enumerate(EVENT_TYPES)], F.sum(F.floor("value")).alias("v"))
    f = {f"f{i}": F.col(f"e{i}") for i in range(5)} | {"f5": F.coalesce("v", F.lit(0))}
    return _with_bg(g, f, {k: F.col(k) for k in ("image_id", "r", "c")})


def vectors(spark: SparkSession, sf_dir: str, dim: int = 6) -> DataFrame:
    """C6: 25 embeddings to an image of 5 x 5; features are the first `dim` components (double)."""
    e = load(spark, sf_dir, "embeddings", "vec_id", "embedding")
    f = [F.get("embedding", i).cast("double").alias(f"f{i}") for i in range(dim)]
    t = e.select(F.expr("vec_id DIV 25").alias("image_id"), F.expr("CAST((vec_id % 25) DIV 5 AS INT)").alias("r"), (F.col("vec_id") % 5).cast("int").alias("c"), *f)
    return t.withColumn("bg", F.sqrt(sum(F.col(f"f{i}") * F.col(f"f{i}") for i in range(dim))))


TAGS = ("a", "li", "p", "div", "script")


def markup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C7: pages as columns of blocks (split before <p and <div); features count tags and letters."""
    p = load(spark, sf_dir, "pages", "page_id", "html")
    blocks = p.select(F.col("page_id").alias("image_id"), F.posexplode(F.split(F.coalesce("html", F.lit("")), "<p>|<div")).alias("r", "block"))
    f = {f"f{i}": F.regexp_count("block", F.lit(f"<{t}[ >]")) for i, t in enumerate(TAGS)} | {"f5": F.length("block")}
    return _with_bg(blocks, f, {"image_id": F.col("image_id"), "r": F.col("r"), "c": F.lit(0)})


KINDS = ("[A-Za-z]", "[0-9]", " ", "[.,;:!?]", "[A-Z]")


def dialogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C8: conversations as turn x sentence grids of character counts."""
    m = load(spark, sf_dir, "conversations", "conv_id", "turn", "text")
    s = m.select(F.col("conv_id").alias("image_id"), F.col("turn").cast("int").alias("r"), F.posexplode(F.split(F.coalesce("text", F.lit("")), "\\.")).alias("c", "s"))
    f = {f"f{i}": F.regexp_count("s", F.lit(k)) for i, k in enumerate(KINDS)} | {"f5": F.length("s")}
    return _with_bg(s, f, {k: F.col(k) for k in ("image_id", "r", "c")})


STRIP_DIM = 16


def strips(texts: DataFrame, id_col: str, text_col: str = "text") -> DataFrame:
    """C5: texts as one-row strips of sentences; features are folded character-bigram counts (a lone
    character counts with 0 behind it)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, place, said, size = [], [], [], 0
            for image, text in zip(b.column("image_id").to_pylist(), b.column("text")):
                own = [x for x in (x.strip(" ") for x in re.split("[.\n]", text.as_py() or "")) if x]
                for a in range(0, len(own), 50_000):  # a very long text goes out in parts
                    part = own[a : a + 50_000]
                    ids += [image] * len(part)
                    place += range(a, a + len(part))
                    said += part
                    size += sum(map(len, part))
                    if size > 2_000_000:
                        yield _strip_rows(ids, place, said)
                        ids, place, said, size = [], [], [], 0
            if ids:
                yield _strip_rows(ids, place, said)

    names = "".join(f", f{j} long" for j in range(STRIP_DIM))
    rows = texts.select(F.col(id_col).cast("long").alias("image_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, f"image_id long, r int, c int{names}, bg long")


def _strip_rows(ids: list, place: list, said: list[str]) -> pa.RecordBatch:
    code = np.frombuffer("".join(said).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.int64)
    size = np.array([len(x) for x in said])
    end = np.cumsum(size) - 1
    pair = (code * 31 + np.append(code[1:], 0)) % STRIP_DIM
    pair[end] = code[end] * 31 % STRIP_DIM
    keep = np.ones(len(code), bool)
    keep[end[size > 1]] = False  # a sentence's last character begins no pair
    row = np.repeat(np.arange(len(said)) * STRIP_DIM, size)
    f = np.bincount((row + pair)[keep], minlength=len(said) * STRIP_DIM).reshape(-1, STRIP_DIM).astype(np.int64)
    columns = [pa.array(ids, pa.int64()), pa.array(np.zeros(len(ids), np.int32)), pa.array(place, pa.int32()), *map(pa.array, f.T.copy()), pa.array(f.sum(1))]
    return pa.RecordBatch.from_arrays(columns, ["image_id", "r", "c", *(f"f{j}" for j in range(STRIP_DIM)), "bg"])


def glyph(spark: SparkSession, sf_dir: str, dim: int = 6, sample: int = 16) -> DataFrame:
    """C4: texts as rasters of characters, 8 x 8 tiles; features are the structure histogram's first
    `dim` principal components in thousandths, bg the L1 distance to a blank tile's.

    The components are learned from one in `sample` images by hash (a documented sample of a
    model's training rows); every tile is projected."""
    tiles = D.glyph_tiles(load(spark, sf_dir, "documents", "doc_id", "text"))
    some = D.describe(tiles.filter(F.pmod(F.xxhash64("image_id"), F.lit(sample)) == 0))
    model = D.fit_pca(some)
    blank = (D.structure_histogram(np.full((1, D.TILE**2), ord(" "))) - model.mean) @ model.components[:dim].T
    out = D.describe(tiles, model=model, dim=dim)
    f = [f"f{i}" for i in range(dim)]
    out = out.select("image_id", "r", "c", *[F.round(F.col(x) * 1000).alias(x) for x in f])
    return out.withColumn("bg", sum(F.abs(F.col(x) - float(np.round(v * 1000))) for x, v in zip(f, blank[0])))


def planted(tiles: DataFrame, h: int, w: int, occluded: float = 0.0, gray: int = 0, rows: int = ROWS, columns: int = COLUMNS) -> DataFrame:
    """C9: an empty (or constant gray) host for each image with a patch of the image pasted at an
    offset given by its id; the patch's leftmost columns come from the next image instead."""
    f = feature_columns(tiles)
    hide = int(occluded * w)
    n = tiles.select("image_id").distinct().count()
    host = (F.col("image_id") + n - F.when(F.col("k") == 1, F.lit(1)).otherwise(F.lit(0))) % n
    both = tiles.withColumn("k", F.explode(F.array(F.lit(0), F.lit(1)))).withColumn("host", host)
    col = F.col("c") - (F.col("host") * 5) % (columns - w + 1)
    row = F.col("r") - F.col("host") % (rows - h + 1)
    inside = (col >= 0) & (col < w) & (row >= 0) & (row < h) & F.when(F.col("k") == 1, col < hide).otherwise(col >= hide)
    patch = both.filter(inside).select(F.col("host").alias("image_id"), "r", "c", *f)
    cells = tiles.select("image_id").distinct().withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(rows * columns - 1))))
    cells = cells.select("image_id", F.expr(f"CAST(i DIV {columns} AS INT)").alias("r"), (F.col("i") % columns).cast("int").alias("c"))
    out = cells.join(patch, ["image_id", "r", "c"], "left").select("image_id", "r", "c", *[F.coalesce(x, F.lit(gray)).alias(x) for x in f])
    return out.withColumn("bg", sum(F.abs(F.col(x)) for x in f))
