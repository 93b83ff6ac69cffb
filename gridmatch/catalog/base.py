"""The standard carrier and queries of the catalogue, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..carriers import grids
from ..overlap.placements import Query
from ..region.solvers import CORNERS, connected_masks, sweep_order
from ..score.functions import ScoreSpec

SPEC = ScoreSpec("l1", 1, 150)
K = 10
#: name -> (image, first row, first column, rows, columns)
PATCHES = {"p22": (3, 2, 4, 2, 2), "p13": (3, 2, 4, 1, 3), "p23": (3, 2, 4, 2, 3), "p33": (3, 2, 4, 3, 3), "p25": (3, 2, 4, 2, 5), "p34": (3, 2, 4, 3, 4)}


def tiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return grids.calendar(spark, sf_dir)


def patch(t: DataFrame, name: str = "p22") -> Query:
    return Query.from_image(t, *PATCHES[name])


F6 = [f"f{i}" for i in range(6)]

CAL = """cal AS (SELECT l_suppkey image_id, CAST(year(l_shipdate) - 1995 AS INTEGER) r, CAST(month(l_shipdate) - 1 AS INTEGER) c,
  count(*) * 10 f0, CAST(sum(l_quantity) AS BIGINT) // 2 f1, CAST(sum(floor(l_extendedprice / 1000)) AS BIGINT) // 5 f2,
  CAST(sum(CAST(round(l_discount * 100) AS BIGINT)) AS BIGINT) * 2 f3, CAST(sum(CAST(round(l_tax * 100) AS BIGINT)) AS BIGINT) * 2 f4,
  count(*) FILTER (l_returnflag = 'R') * 10 f5 FROM lineitem GROUP BY 1, 2, 3)"""
TILES = f"""{CAL}, grid AS (SELECT image_id, CAST(i // 12 AS INTEGER) r, CAST(i % 12 AS INTEGER) c FROM (SELECT DISTINCT image_id FROM cal), range(84) g(i)),
tiles AS (SELECT g.image_id, g.r, g.c, {', '.join(f'coalesce({f}, 0) {f}' for f in F6)}, {' + '.join(f'coalesce({f}, 0)' for f in F6)} bg
  FROM grid g LEFT JOIN cal ON cal.image_id = g.image_id AND cal.r = g.r AND cal.c = g.c)"""


def qtiles(name: str) -> str:
    image, r0, c0, h, w = PATCHES[name]
    cols = ", ".join(f"f{i} q{i}" for i in range(6))
    return f"qt AS (SELECT CAST((r - {r0}) * {w} + c - {c0} AS INTEGER) q, r - {r0} qr, c - {c0} qc, bg qbg, {cols} FROM tiles WHERE image_id = {image} AND r BETWEEN {r0} AND {r0 + h - 1} AND c BETWEEN {c0} AND {c0 + w - 1})"


DIST = " + ".join(f"abs(f{i} - q{i})" for i in range(6))


def cells_sql(name: str, c: int = 150) -> str:
    """CTEs up to `cells` (image_id, dr, dc, q, dist, score)."""
    return f"{TILES}, {qtiles(name)}, cells AS (SELECT image_id, r - qr dr, c - qc dc, q, qr, qc, CAST({DIST} AS BIGINT) dist, CAST(qbg - ({DIST}) - {c} AS BIGINT) score FROM tiles, qt)"


def wide_sql(name: str, c: int = 150) -> str:
    n = PATCHES[name][3] * PATCHES[name][4]
    cols = ", ".join(f"max(score) FILTER (q = {i}) s{i}" for i in range(n))
    return f"{cells_sql(name, c)}, wide AS (SELECT image_id, dr, dc, {cols} FROM cells GROUP BY 1, 2, 3)"


def _pick(options: list[str]) -> str:
    return f"list_aggregate(list_filter([{', '.join(options)}], lambda x: x.s IS NOT NULL), 'max')"


def _struct(s: str, m: str) -> str:
    return f"struct_pack(s := CAST({s} AS BIGINT), n := -bit_count(CAST({m} AS BIGINT)), m := -CAST({m} AS BIGINT))"


def exact_sql(name: str, c: int = 150, source: str = "wide") -> str:
    """CTEs up to `best` (image_id, dr, dc, b): the best connected mask."""
    h, w = PATCHES[name][3:]
    options = [_struct(" + ".join(f"s{i}" for i in range(h * w) if m >> i & 1), str(m)) for m in connected_masks(h, w)]
    return f"{wide_sql(name, c)}, best AS (SELECT image_id, dr, dc, {_pick(options)} b FROM {source})"


def sweep_sql(name: str, corner: str, c: int = 150) -> str:
    """CTEs up to `sw_<corner>` (image_id, dr, dc, b): one sweep, a CTE for each cell."""
    h, w = PATCHES[name][3:]
    n, parts, last = h * w, [], "wide"
    for i, row, col in sweep_order(h, w, corner):
        options = [_struct(f"s{i}", str(1 << i))]
        for j in (row, col):
            if j >= 0:
                options.append(_struct(f"s{i} + g{j}.s", f"({1 << i} | (-g{j}.m))"))
        if row >= 0 and col >= 0:
            both = " + ".join(f"CASE WHEN ((-g{row}.m) & (-g{col}.m)) & {1 << k} <> 0 THEN coalesce(s{k}, 0) ELSE 0 END" for k in range(n))
            options.append(_struct(f"s{i} + g{row}.s + g{col}.s - ({both})", f"({1 << i} | (-g{row}.m) | (-g{col}.m))"))
        name_i = f"{corner.lower()}_{i}"
        parts.append(f"{name_i} AS (SELECT *, {_pick(options)} g{i} FROM {last})")
        last = name_i
    ends = [f"g{i}" for i in range(n)]
    parts.append(f"sw_{corner} AS (SELECT image_id, dr, dc, list_aggregate(list_filter([{', '.join(ends)}], lambda x: x.s IS NOT NULL), 'max') b FROM {last})")
    return ", ".join(parts)


def corner_sql(name: str, c: int = 150) -> str:
    """CTEs up to `best`: the best of the four sweeps."""
    parts = [sweep_sql(name, k, c) for k in CORNERS]
    joins = " ".join(f"JOIN sw_{k} USING (image_id, dr, dc)" for k in CORNERS[1:])
    return f"{wide_sql(name, c)}, {', '.join(parts)}, best AS (SELECT image_id, dr, dc, list_aggregate([{', '.join(f'sw_{k}.b' for k in CORNERS)}], 'max') b FROM sw_BL {joins})"


REGION = "b.s score, CAST(-b.n AS INTEGER) n_cells, -b.m mask"


def topk_sql(ctes: str, k: int = K, where: str = "") -> str:
    return f"WITH {ctes} SELECT image_id, dr, dc, {REGION} FROM best {where} ORDER BY score DESC, image_id, dr, dc LIMIT {k}"


def hits(df: DataFrame) -> DataFrame:
    """The columns of a result that the SQL gives, scores as whole numbers."""
    return df.selectExpr("image_id", "dr", "dc", "CAST(score AS BIGINT) score", "n_cells", "mask")
