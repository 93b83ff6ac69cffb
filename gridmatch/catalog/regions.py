"""Scores, distances, overlaps and regions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..carriers import grids
from ..carriers.grids import feature_columns
from ..overlap import placements as P
from ..region import expressions, solvers
from ..score import functions as S
from .base import CORNERS, DIST, REGION, SPEC, cells_sql, corner_sql, exact_sql, patch, qtiles, sweep_sql, tiles, wide_sql, TILES

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def _pairs(spark, d, name="p22", metric="l1"):
    t = tiles(spark, d)
    return P.pairs(t, P.query_tiles(spark, patch(t, name)), metric)


PAIR = f"WITH {TILES}, {qtiles('p22')}, p AS (SELECT image_id, r, c, q, qbg, CAST({DIST} AS BIGINT) dist, * EXCLUDE (image_id, r, c, q, qbg) FROM tiles, qt)"


#: What a grid of values comes to for each image and query tile: enough to tell any value or place apart.
DIGEST = "count(*) n, CAST(sum(v) AS BIGINT) total, CAST(min(v) AS BIGINT) low, CAST(max(v) AS BIGINT) high, CAST(sum(v * pos) AS BIGINT) placed"


def digest(df, value, at):
    x = df.withColumn("v", value).withColumn("pos", at.cast("long"))
    return x.groupBy("image_id", "q").agg(F.count("*").alias("n"), F.sum("v").alias("total"), F.min("v").alias("low"), F.max("v").alias("high"), F.sum(F.col("v") * F.col("pos")).alias("placed"))


def digest_sql(ctes: str, value: str, at: str, source: str) -> str:
    return f"{ctes} SELECT image_id, q, {DIGEST} FROM (SELECT image_id, q, CAST({value} AS BIGINT) v, CAST({at} AS BIGINT) pos FROM {source}) GROUP BY 1, 2"


def _scored(name, column, sql):
    """Scores in thousandths, by image and query tile."""

    @query(name, digest_sql(PAIR, f"round(({sql}) * 1000)", "r * 12 + c + 1", "p"))
    def run(spark, d):
        return digest(_pairs(spark, d), F.round(column() * 1000).cast("long"), F.col("r") * 12 + F.col("c") + 1)


bg, di = lambda: F.col("qbg"), lambda: F.col("dist")
_scored("score_discriminator", lambda: S.discriminator_score(bg(), di(), 1, 150), "qbg - dist - 150")
_scored("score_log_odds", lambda: S.log_odds_score(bg().cast("double"), di().cast("double"), 0.02, 0.01), "0.01::DOUBLE * qbg - 0.02::DOUBLE * dist + ln(2.0::DOUBLE)")
_scored("score_template_sqrt", lambda: S.template_score(bg().cast("double"), di().cast("double"), "sqrt", 150), "qbg - sqrt(dist) - 150")
_scored("score_template_square", lambda: S.template_score(bg(), di(), "square", 150), "qbg - dist * dist - 150")
_scored("score_template_capped", lambda: S.template_score(bg().cast("double"), di().cast("double"), "capped", 150), "qbg - least(dist, 1000.0::DOUBLE) - 150")


@query("score_equivalence", f"{PAIR} SELECT q, count(*) n, true same FROM p GROUP BY q")
def score_equivalence(spark, d):
    lam, c = S.to_discriminator(0.02, 0.01)
    p = _pairs(spark, d)
    a = S.log_odds_score(F.col("qbg").cast("double"), F.col("dist").cast("double"), 0.02, 0.01)
    b = 0.01 * S.discriminator_score(F.col("qbg").cast("double"), F.col("dist").cast("double"), lam, c)
    return p.groupBy("q").agg(F.count("*").alias("n"), F.bool_and(F.abs(a - b) < 1e-6).alias("same"))


LINF = "greatest(" + ", ".join(f"abs(f{i} - q{i})" for i in range(6)) + ")"
L2 = "sqrt(CAST(" + " + ".join(f"(f{i} - q{i}) * (f{i} - q{i})" for i in range(6)) + " AS DOUBLE))"
for _m, _sql in (("l1", "dist"), ("l2", L2), ("linf", LINF)):

    @query(f"distance_{_m}", digest_sql(PAIR, f"round(({_sql}) * 1000)", "r * 12 + c + 1", "p"))
    def distances(spark, d, m=_m):
        return digest(_pairs(spark, d, metric=m), F.round(F.col("dist") * 1000).cast("long"), F.col("r") * 12 + F.col("c") + 1)


@query("histogram_emd", f"WITH {TILES} SELECT image_id, r, c, CAST(abs(f0 - f3) + abs(f0 + f1 - f3 - f4) + abs(f0 + f1 + f2 - f3 - f4 - f5) AS BIGINT) emd FROM tiles")
def histogram_emd(spark, d):
    return tiles(spark, d).select("image_id", "r", "c", S.emd(F.array("f0", "f1", "f2"), F.array("f3", "f4", "f5")).cast("long").alias("emd"))


BOX = "b AS (SELECT image_id, " + ", ".join(f"min(f{i}) lo{i}, max(f{i}) hi{i}" for i in range(6)) + " FROM tiles GROUP BY 1)"


@query("mindist_boxes", f"WITH {TILES}, {qtiles('p22')}, {BOX} SELECT image_id, q, CAST({' + '.join(f'greatest(lo{i} - q{i}, 0, q{i} - hi{i})' for i in range(6))} AS BIGINT) d FROM b, qt")
def mindist_boxes(spark, d):
    t = tiles(spark, d)
    f = feature_columns(t)
    b = t.groupBy("image_id").agg(*[F.min(x).alias(f"lo_{x}") for x in f], *[F.max(x).alias(f"hi_{x}") for x in f])
    x = b.crossJoin(F.broadcast(P.query_tiles(spark, patch(t))))
    return x.select("image_id", "q", S.mindist([F.col(f"q{i}") for i in range(6)], [F.col(f"lo_{k}") for k in f], [F.col(f"hi_{k}") for k in f]).cast("long").alias("d"))


@query("background_zero", f"WITH {TILES} SELECT image_id, r, c, CAST(bg AS BIGINT) bg FROM tiles")
def background_zero(spark, d):
    return tiles(spark, d).select("image_id", "r", "c", "bg")


@query("background_gray", f"WITH {TILES} SELECT image_id, r, c, CAST({' + '.join(f'abs(f{i} - 40)' for i in range(6))} AS BIGINT) bg FROM tiles")
def background_gray(spark, d):
    t = tiles(spark, d)
    return t.select("image_id", "r", "c", S.dist([F.col(x) for x in feature_columns(t)], [F.lit(40)] * 6).alias("bg"))


SHAPES = f"WITH {TILES}, s AS (SELECT image_id, max(r) + 1 nr, max(c) + 1 nc FROM tiles GROUP BY 1)"


@query("overlaps_all", f"{SHAPES} SELECT image_id, dr, dc FROM s, (SELECT CAST(unnest(range(-1, 7)) AS INTEGER) dr), (SELECT CAST(unnest(range(-1, 12)) AS INTEGER) dc)")
def overlaps_all(spark, d):
    return P.enumerate_overlaps(P.image_shapes(tiles(spark, d)), 2, 2)


@query("overlaps_inside", f"{SHAPES} SELECT image_id, dr, dc FROM s, (SELECT CAST(unnest(range(0, 6)) AS INTEGER) dr), (SELECT CAST(unnest(range(0, 11)) AS INTEGER) dc)")
def overlaps_inside(spark, d):
    return P.enumerate_overlaps(P.image_shapes(tiles(spark, d)), 2, 2, "inside")


@query("overlap_counts", f"{SHAPES} SELECT h, w, CAST(sum((nr + h - 1) * (nc + w - 1)) AS BIGINT) n_overlaps FROM s, (VALUES (2, 2), (2, 5), (4, 5), (5, 6), (4, 10)) v(h, w) GROUP BY 1, 2")
def overlap_counts(spark, d):
    s = P.image_shapes(tiles(spark, d))
    out = None
    for h, w in ((2, 2), (2, 5), (4, 5), (5, 6), (4, 10)):
        x = P.overlap_count(s, h, w).select(F.lit(h).alias("h"), F.lit(w).alias("w"), F.col("overlaps").alias("n_overlaps"))
        out = x if out is None else out.union(x)
    return out


@query("overlaps_from_pairs", f"{PAIR} SELECT DISTINCT image_id, r - qr dr, c - qc dc FROM p WHERE dist < 200")
def overlaps_from_pairs(spark, d):
    return _pairs(spark, d).filter("dist < 200").select("image_id", "dr", "dc").distinct()


def _dihedral_sql():
    """The best alignment of each rotated or reflected query: its cells are the query's, moved."""
    grid, parts = np.arange(4).reshape(2, 2), []
    for k, g in enumerate(x for turn in range(4) for x in (np.rot90(grid, turn), np.fliplr(np.rot90(grid, turn)))):
        moved = ", ".join(f"({i}, {o})" for i, o in enumerate(g.ravel().tolist()))
        qt = f"qt AS (SELECT CAST(i AS INTEGER) q, i // 2 qr, i % 2 qc, qbg, {', '.join(f'q{j}' for j in range(6))} FROM qt0 JOIN (VALUES {moved}) m(i, o) ON q = o)"
        ctes = exact_sql("p22").replace("qt AS (", "qt0 AS (", 1).replace(", cells AS", f", {qt}, cells AS", 1)
        parts.append(f"SELECT CAST({k} AS BIGINT) query_id, * FROM (WITH {ctes} SELECT image_id, dr, dc, CAST(b.s AS BIGINT) score FROM best ORDER BY score DESC, image_id, dr, dc LIMIT 3)")
    return " UNION ALL ".join(parts)


@query("overlaps_dihedral", _dihedral_sql())
def overlaps_dihedral(spark, d):
    """Three best alignments of each of the eight rotated and reflected queries, searched together."""
    from ..search import algorithms as A

    t = tiles(spark, d)
    return A.scan(t, P.dihedral(patch(t)), 3, SPEC).df.select("query_id", "image_id", "dr", "dc", F.col("score").cast("long").alias("score"))


PLACED = "(dr + 1) * 13 + dc + 2"


@query("score_cells_p22", digest_sql(f"WITH {cells_sql('p22')}", "score", PLACED, "cells"))
def score_cells(spark, d):
    t = tiles(spark, d)
    return digest(P.cells(t, P.query_tiles(spark, patch(t)), SPEC), F.col("score"), F.expr(PLACED))


@query("distance_cells_p22", digest_sql(f"WITH {cells_sql('p22')}", "dist", PLACED, "cells"))
def distance_cells(spark, d):
    t = tiles(spark, d)
    return digest(P.cells(t, P.query_tiles(spark, patch(t)), SPEC), F.col("dist"), F.expr(PLACED))


def wide(spark, d, name="p22", spec=SPEC):
    t = tiles(spark, d)
    q = patch(t, name)
    return P.matrices(P.cells(t, P.query_tiles(spark, q), spec), q.n).drop("query_id"), q


@query("score_matrices_p33", f"WITH {wide_sql('p33')} SELECT image_id, dr, dc, {', '.join(f'coalesce(s{i}, -999999) s{i}' for i in range(9))} FROM wide")
def score_matrices(spark, d):
    return wide(spark, d, "p33")[0].fillna(-999999)


@query("virtual_uniform_bound", f"WITH {TILES}, {qtiles('p22')}, v AS (SELECT d, sum(greatest(qbg - d - 150, 0)) p, max(qbg - d - 150) m FROM qt, (SELECT unnest(range(0, 1000, 50)) d) GROUP BY d) SELECT CAST(d AS BIGINT) d, CAST(CASE WHEN m > 0 THEN p ELSE m END AS BIGINT) bound FROM v")
def virtual_uniform_bound(spark, d):
    q = patch(tiles(spark, d))
    at = spark.range(0, 1000, 50).select(F.col("id").alias("d"))
    score = [SPEC.column(F.lit(int(x)), F.col("d")) for x in q.bg]
    return at.select("d", expressions.positive_sum(score).cast("long").alias("bound"))


@query("virtual_last_seen_bound", f"{PAIR}, n AS (SELECT q, qbg, dist, row_number() OVER (PARTITION BY q ORDER BY dist, image_id, r, c) k FROM p), v AS (SELECT k, sum(greatest(qbg - dist - 150, 0)) p, max(qbg - dist - 150) m FROM n WHERE k <= 50 GROUP BY k) SELECT k, CAST(CASE WHEN m > 0 THEN p ELSE m END AS BIGINT) bound FROM v")
def virtual_last_seen_bound(spark, d):
    from ..index.packed import sorted_access

    t = tiles(spark, d)
    qt = P.query_tiles(spark, patch(t))
    n = sorted_access(t, qt, SPEC, 50).join(F.broadcast(qt.select("q", "qbg")), "q").withColumn("s", F.col("qbg") - F.col("dist") - 150)
    g = n.groupBy(F.col("nn").cast("long").alias("k")).agg(F.sum(F.greatest("s", F.lit(0))).alias("p"), F.max("s").alias("m"))
    return g.select("k", F.when(F.col("m") > 0, F.col("p")).otherwise(F.col("m")).cast("long").alias("bound"))


SWEPT = "image_id, dr, dc, " + REGION
for _k in CORNERS:

    @query(f"sweep_{_k.lower()}_p22", f"WITH {wide_sql('p22')}, {sweep_sql('p22', _k)} SELECT {SWEPT} FROM sw_{_k}")
    def one_sweep(spark, d, k=_k):
        df, q = wide(spark, d)
        r = expressions.sweep(df, q.h, q.w, k)
        return r.select("image_id", "dr", "dc", F.col("region.s").alias("score"), (-F.col("region.n")).alias("n_cells"), (-F.col("region.m")).alias("mask"))


def solved(df, q, solver="corner_dp"):
    """image_id, dr, dc, score, n_cells, mask by the numpy solvers in Arrow batches."""
    import pyarrow as pa

    h, w, n = q.h, q.w, q.n

    def run(batches):
        for b in batches:
            m = np.stack([b.column(f"s{i}").cast(pa.float64()).to_numpy(zero_copy_only=False) for i in range(n)], 1)
            s, mask = solvers.solve(m, h, w, solver)
            yield pa.RecordBatch.from_arrays([b.column("image_id"), b.column("dr"), b.column("dc"), pa.array(s.astype(np.int64)), pa.array(np.bitwise_count(mask).astype(np.int32)), pa.array(mask)], ["image_id", "dr", "dc", "score", "n_cells", "mask"])

    return df.mapInArrow(run, "image_id long, dr int, dc int, score long, n_cells int, mask long")


for _p in ("p22", "p23"):

    @query(f"corner_dp_{_p}", f"WITH {corner_sql(_p)} SELECT {SWEPT} FROM best")
    def corner_dp(spark, d, p=_p):
        return solved(*wide(spark, d, p))


@query("corner_dp_expr_p22", f"WITH {corner_sql('p22')} SELECT {SWEPT} FROM best")
def corner_dp_expr(spark, d):
    df, q = wide(spark, d)
    return expressions.corner_dp(df, q.h, q.w).select("image_id", "dr", "dc", "score", "n_cells", "mask")


for _p in ("p22", "p23", "p33"):

    @query(f"exact_region_{_p[1]}x{_p[2]}", f"WITH {exact_sql(_p)} SELECT {SWEPT} FROM best")
    def exact_region(spark, d, p=_p):
        return solved(*wide(spark, d, p), "exact")


@query("exact_region_expr_2x2", f"WITH {exact_sql('p22')} SELECT {SWEPT} FROM best")
def exact_expr(spark, d):
    df, q = wide(spark, d)
    return expressions.exact(df, q.h, q.w).select("image_id", "dr", "dc", "score", "n_cells", "mask")


def _gap_sql():
    dp = corner_sql("p23").replace(", best AS", ", dp AS")
    ex = exact_sql("p23").split(", best AS", 1)[1]
    return f"WITH {dp}, best AS{ex} SELECT count(*) n, count(*) FILTER (dp.b.s < best.b.s) n_below, CAST(sum(best.b.s - dp.b.s) AS BIGINT) lost FROM dp JOIN best USING (image_id, dr, dc)"


@query("dp_gap_2x3", _gap_sql())
def dp_gap(spark, d):
    df, q = wide(spark, d, "p23")
    a = solved(df, q).select("image_id", "dr", "dc", F.col("score").alias("dp"))
    b = solved(df, q, "exact").select("image_id", "dr", "dc", F.col("score").alias("ex"))
    j = a.join(b, ["image_id", "dr", "dc"])
    return j.agg(F.count("*").alias("n"), F.sum((F.col("dp") < F.col("ex")).cast("long")).alias("n_below"), F.sum(F.col("ex") - F.col("dp")).alias("lost"))


RUN = f"""WITH {cells_sql('p13')}, x AS (SELECT image_id, dr, dc, qc, score, sum(score) OVER w s, coalesce(sum(score) OVER (PARTITION BY image_id, dr, dc ORDER BY qc ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) b FROM cells WINDOW w AS (PARTITION BY image_id, dr, dc ORDER BY qc)),
y AS (SELECT *, min(b) OVER (PARTITION BY image_id, dr, dc ORDER BY qc) low FROM x) SELECT image_id, dr, dc, CAST(max(s - low) AS BIGINT) score FROM y GROUP BY 1, 2, 3"""


@query("best_run_p13", RUN)
def best_run(spark, d):
    """Window form: running sum less the smallest earlier one."""
    from pyspark.sql import Window

    t = tiles(spark, d)
    c = P.cells(t, P.query_tiles(spark, patch(t, "p13")), SPEC)
    w = Window.partitionBy("image_id", "dr", "dc").orderBy("qc")
    x = c.withColumn("s", F.sum("score").over(w)).withColumn("b", F.col("s") - F.col("score"))
    return x.withColumn("low", F.min("b").over(w)).groupBy("image_id", "dr", "dc").agg(F.max(F.col("s") - F.col("low")).alias("score"))


@query("best_run_arrow_p13", RUN)
def best_run_arrow(spark, d):
    return solved(*wide(spark, d, "p13"), "best_run").select("image_id", "dr", "dc", "score")


@query("positive_sum_bounds", f"WITH {cells_sql('p22')} SELECT image_id, dr, dc, CAST(CASE WHEN max(score) > 0 THEN sum(greatest(score, 0)) ELSE max(score) END AS BIGINT) bound FROM cells GROUP BY 1, 2, 3")
def positive_sum_bounds(spark, d):
    from ..search.algorithms import overlap_bounds

    t = tiles(spark, d)
    return overlap_bounds(t, patch(t), SPEC).select("image_id", "dr", "dc", "bound")


@query("region_edges", f"WITH {exact_sql('p22')}, m AS (SELECT image_id, dr, dc, -b.m m FROM best) SELECT image_id, dr, dc, CAST(i AS INTEGER) i, CAST(j AS INTEGER) j FROM m, (VALUES (0, 1), (0, 2), (1, 3), (2, 3)) e(i, j) WHERE m & (1 << i) <> 0 AND m & (1 << j) <> 0")
def region_edges(spark, d):
    df, q = wide(spark, d)
    r = expressions.exact(df, 2, 2)
    e = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in range(4) for j in solvers.neighbours(i, 2, 2) if i < j])).alias("e")
    has = lambda k: F.col("mask").bitwiseAND(F.shiftleft(F.lit(1).cast("long"), 0) * F.pow(F.lit(2), k).cast("long")) != 0
    return r.select("image_id", "dr", "dc", "mask", e).filter(has(F.col("e.i")) & has(F.col("e.j"))).select("image_id", "dr", "dc", "e.i", "e.j")


@query("decision_region", f"WITH {exact_sql('p22')} SELECT image_id, dr, dc, b.s >= 300 yes FROM best")
def decision_region(spark, d):
    df, _ = wide(spark, d)
    return expressions.exact(df, 2, 2).select("image_id", "dr", "dc", (F.col("score") >= 300).alias("yes"))


#: Cells and moves of a 2 x 3 grid, and what reaches what inside each mask.
REACH = """WITH RECURSIVE masks AS (SELECT m FROM range(1, 64) g(m)), cell AS (SELECT m, i FROM masks, range(6) g(i) WHERE m & (1 << CAST(i AS INTEGER)) <> 0),
corner AS (SELECT * FROM (VALUES ('BL', 1, 1), ('BR', 1, -1), ('TL', -1, 1), ('TR', -1, -1), ('all', 1, 1)) v(k, dr, dc)),
step AS (SELECT k, a.i, b.i j FROM corner, range(6) a(i), range(6) b(i) WHERE (b.i // 3 - a.i // 3 = dr AND b.i % 3 = a.i % 3) OR (b.i // 3 = a.i // 3 AND b.i % 3 - a.i % 3 = dc) OR (k = 'all' AND abs(b.i // 3 - a.i // 3) + abs(b.i % 3 - a.i % 3) = 1)),
reach AS (SELECT m, k, i src, i dst FROM cell, corner UNION SELECT r.m, r.k, r.src, s.j FROM reach r JOIN step s ON s.k = r.k AND s.i = r.dst JOIN cell c ON c.m = r.m AND c.i = s.j),
met AS (SELECT m, k, dst, count(DISTINCT src) n FROM reach GROUP BY 1, 2, 3), most AS (SELECT m, k, max(n) = bit_count(CAST(m AS BIGINT)) yes FROM met GROUP BY 1, 2)"""


#: The foreground of every 2 x 3 block of an image's first six rows as a mask.
BLOCKS = f"{TILES}, blocks AS (SELECT image_id, CAST(r // 2 * 4 + c // 3 AS INTEGER) block, CAST(sum(CASE WHEN bg >= 385 THEN 1 << CAST(r % 2 * 3 + c % 3 AS INTEGER) ELSE 0 END) AS BIGINT) m FROM tiles WHERE r < 6 GROUP BY 1, 2)"


def _masks(spark, d):
    bit = F.expr("shiftleft(1L, r % 2 * 3 + c % 3)")
    at = F.expr("CAST(r DIV 2 * 4 + c DIV 3 AS INT)").alias("block")
    return tiles(spark, d).filter("r < 6").groupBy("image_id", at).agg(F.sum(F.when(F.col("bg") >= 385, bit).otherwise(F.lit(0))).alias("mask")).filter("mask <> 0")


@query("region_connected", f"{REACH}, {BLOCKS} SELECT image_id, block, m mask, yes connected FROM blocks JOIN most USING (m) WHERE k = 'all'")
def region_connected(spark, d):
    """Connectivity of the foreground of every 2 x 3 block."""
    return _masks(spark, d).select("image_id", "block", "mask", expressions.connected(F.col("mask"), 2, 3).alias("connected"))


@query("region_sink_class", f"{REACH}, {BLOCKS}, sinks AS (SELECT a.m, string_agg(CASE WHEN b.yes THEN b.k END, ',' ORDER BY b.k) sinks FROM most a JOIN most b ON a.m = b.m AND a.k = 'all' AND b.k <> 'all' AND a.yes GROUP BY 1) SELECT image_id, block, m mask, sinks FROM blocks JOIN sinks USING (m)")
def region_sink_class(spark, d):
    """The corners whose sweeps can give each block's foreground, where it is connected."""
    m = _masks(spark, d).filter(expressions.connected(F.col("mask"), 2, 3))
    return m.select("image_id", "block", "mask", F.nullif(F.concat_ws(",", *[F.when(expressions.has_sink(F.col("mask"), 2, 3, k), F.lit(k)) for k in sorted(CORNERS)]), F.lit("")).alias("sinks"))


@query("region_algebra", f"WITH {exact_sql('p22')}, x AS (SELECT image_id, max(-b.m) FILTER (dr = 0 AND dc = 0) a, max(-b.m) FILTER (dr = 1 AND dc = 1) b FROM best GROUP BY 1) SELECT image_id, a | b joined, a & b common FROM x")
def region_algebra(spark, d):
    """Union and intersection of two alignments' best regions in each image."""
    df, _ = wide(spark, d)
    r = expressions.exact(df, 2, 2)
    at = lambda k: F.max(F.when((F.col("dr") == k) & (F.col("dc") == k), F.col("mask")))
    g = r.groupBy("image_id").agg(at(0).alias("a"), at(1).alias("b"))
    return g.select("image_id", expressions.region_union(F.col("a"), F.col("b")).alias("joined"), expressions.region_intersect(F.col("a"), F.col("b")).alias("common"))


STEINER = f"""WITH {TILES}, t AS (SELECT image_id, r * 2 r, c * 2 c FROM tiles WHERE r < 3 AND c < 3 AND bg >= 450), x AS (SELECT DISTINCT image_id FROM tiles),
g AS (SELECT image_id, CAST(r AS INTEGER) r, CAST(c AS INTEGER) c FROM x, range(5) a(r), range(5) b(c) WHERE NOT (r % 2 = 1 AND c % 2 = 1))
SELECT g.image_id, g.r, g.c, CAST(CASE WHEN g.r % 2 = 1 OR g.c % 2 = 1 THEN -1 WHEN t.r IS NULL THEN 0 ELSE 19 END AS BIGINT) score FROM g LEFT JOIN t ON t.image_id = g.image_id AND t.r = g.r AND t.c = g.c"""


@query("steiner_instance_cells", STEINER)
def steiner_instance_cells(spark, d):
    """The tree problem whose terminals are the fullest of each image's first 3 x 3 tiles, as a score matrix."""
    import pyarrow as pa

    full = F.when(F.col("bg") >= 450, F.expr("shiftleft(1L, r * 3 + c)")).otherwise(F.lit(0))
    points = tiles(spark, d).filter("r < 3 AND c < 3").groupBy("image_id").agg(F.sum(full).alias("mask"))

    def run(batches):
        made = {}
        for b in batches:
            masks = b.column("mask").to_pylist()
            for m in set(masks) - set(made):
                s, _, _ = solvers.steiner_instance(set(solvers.region_cells(m, 3)), 3, 4)
                made[m] = (*np.nonzero(~np.isnan(s)), s[~np.isnan(s)].astype(np.int64))
            r, c, score = (np.concatenate(x) if masks else np.zeros(0) for x in (zip(*(made[m] for m in masks)) if masks else ((),) * 3))
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(b.column("image_id").to_numpy(), 21)), pa.array(r.astype(np.int32)), pa.array(c.astype(np.int32)), pa.array(score.astype(np.int64))], ["image_id", "r", "c", "score"])

    return points.mapInArrow(run, "image_id long, r int, c int, score long")


def _fig6_sql():
    own = wide_sql("p34").replace("FROM cells GROUP BY", "FROM cells WHERE dr = 2 AND dc = 4 GROUP BY")
    sweeps = " UNION ALL ".join(f"SELECT image_id, '{k}' sweep, b.s score FROM sw_{k}" for k in CORNERS)
    cells = " + ".join(f"s{i} * (m >> {i} & 1)" for i in range(12))
    masks = ", ".join(f"({m})" for m in solvers.connected_masks(3, 4))
    exact = f"SELECT image_id, 'exact' sweep, CAST(max({cells}) AS BIGINT) score FROM wide, (VALUES {masks}) v(m) GROUP BY 1"
    return f"WITH {own}, {', '.join(sweep_sql('p34', k) for k in CORNERS)}, four AS ({sweeps}) SELECT * FROM four UNION ALL SELECT image_id, 'best', max(score) FROM four GROUP BY 1 UNION ALL {exact}"


@query("fig6_sweeps", _fig6_sql())
def fig6_sweeps(spark, d):
    """Each sweep, the best of them and the exact region of a 3 x 4 patch at its own place in every image."""
    import pyarrow as pa

    df, q = wide(spark, d, "p34")

    def run(batches):
        for b in batches:
            m = np.stack([b.column(f"s{i}").cast(pa.float64()).to_numpy(zero_copy_only=False) for i in range(q.n)], 1)
            found = {k: solvers.sweep(m, q.h, q.w, k)[0] for k in CORNERS}
            found |= {"best": solvers.corner_dp(m, q.h, q.w)[0], "exact": solvers.exact_region(m, q.h, q.w)[0]}
            for k, s in found.items():
                yield pa.RecordBatch.from_arrays([b.column("image_id"), pa.array([k] * len(m), pa.string()), pa.array(s.astype(np.int64))], ["image_id", "sweep", "score"])

    return df.filter("dr = 2 AND dc = 4").mapInArrow(run, "image_id long, sweep string, score long")


@query("fig9_overlaps", "WITH s AS (SELECT CAST(c_nationkey AS BIGINT) image_id, max(year(o_orderdate)) - 1994 nr, max(month(o_orderdate)) nc FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1) SELECT image_id, CAST(dr AS INTEGER) dr, CAST(dc AS INTEGER) dc FROM s, range(-1, 1000) a(dr), range(-1, 12) b(dc) WHERE dr < nr AND dc < nc")
def fig9_overlaps(spark, d):
    """Every overlap of a 2 x 2 query on the nations' grids of orders."""
    return P.enumerate_overlaps(P.image_shapes(grids.order_grid(spark, d)), 2, 2)
