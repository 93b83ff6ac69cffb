"""The relational operators around the methods, each on the carriers."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..carriers import grids
from ..durable import saved
from ..overlap import placements as P
from ..tables import load, register
from .base import CAL, SPEC, TILES, cells_sql, corner_sql, exact_sql, patch, sweep_sql, tiles, wide_sql

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


T = f"WITH {TILES}"
C = f"WITH {cells_sql('p22')}"
ALL = "image_id, r, c, CAST(f0 AS BIGINT) f0, CAST(f1 AS BIGINT) f1, CAST(f2 AS BIGINT) f2, CAST(f3 AS BIGINT) f3, CAST(f4 AS BIGINT) f4, CAST(f5 AS BIGINT) f5, CAST(bg AS BIGINT) bg"


def cells(spark, d):
    t = tiles(spark, d)
    return P.cells(t, P.query_tiles(spark, patch(t)), SPEC)


@query("calendar_tiles", f"{T} SELECT {ALL} FROM tiles")
def calendar_tiles(spark, d):
    return tiles(spark, d)


@query("dense_grid", f"{T}, e AS (SELECT g.image_id, count(*) cells, count(cal.r) filled FROM grid g LEFT JOIN cal USING (image_id, r, c) GROUP BY 1) SELECT * FROM e")
def dense_grid(spark, d):
    full, some = tiles(spark, d), grids.calendar(spark, d, fill=False).select("image_id", "r", "c", F.lit(1).alias("x"))
    return full.join(some, ["image_id", "r", "c"], "left").groupBy("image_id").agg(F.count("*").alias("cells"), F.count("x").alias("filled"))


@query("order_tiles", "SELECT CAST(c_nationkey AS BIGINT) image_id, CAST(year(o_orderdate) - 1995 AS INTEGER) r, CAST(month(o_orderdate) - 1 AS INTEGER) c, " + ", ".join(f"count(*) FILTER (o_orderpriority = '{p}') f{i}" for i, p in enumerate(grids.PRIORITIES)) + ", " + ", ".join(f"count(*) FILTER (o_orderstatus = '{s}') f{5 + i}" for i, s in enumerate(grids.STATUSES)) + ", CAST(sum(floor(o_totalprice / 1000)) AS BIGINT) f8 FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2, 3")
def order_tiles(spark, d):
    return grids.order_grid(spark, d).drop("bg")


@query("activity_tiles", "SELECT user_id image_id, CAST(day(ts) - 1 AS INTEGER) r, CAST(hour(ts) // 4 AS INTEGER) c, " + ", ".join(f"count(*) FILTER (event_type = '{t}') f{i}" for i, t in enumerate(grids.EVENT_TYPES)) + ", CAST(coalesce(sum(floor(value)), 0) AS BIGINT) f5 FROM events GROUP BY 1, 2, 3")
def activity_tiles(spark, d):
    return grids.activity(spark, d).drop("bg")


@query("vector_tiles", "SELECT vec_id // 25 image_id, CAST((vec_id % 25) // 5 AS INTEGER) r, CAST(vec_id % 5 AS INTEGER) c, round(embedding[1]::DOUBLE, 6) f0, round(embedding[3]::DOUBLE, 6) f2 FROM embeddings")
def vector_tiles(spark, d):
    return grids.vectors(spark, d, 3).select("image_id", "r", "c", F.round("f0", 6).alias("f0"), F.round("f2", 6).alias("f2"))


@query("markup_tiles", "WITH b AS (SELECT page_id, unnest(regexp_split_to_array(coalesce(html, ''), '<p>|<div')) block FROM pages) SELECT page_id image_id, count(*) blocks, CAST(sum(length(block)) AS BIGINT) chars, CAST(sum(len(regexp_extract_all(block, '<a[ >]'))) AS BIGINT) links FROM b GROUP BY 1")
def markup_tiles(spark, d):
    return grids.markup(spark, d).groupBy("image_id").agg(F.count("*").alias("blocks"), F.sum("f5").alias("chars"), F.sum("f0").alias("links"))


@query("dialogue_tiles", "WITH s AS (SELECT conv_id, turn, unnest(string_split(coalesce(text, ''), '.')) s FROM conversations) SELECT conv_id image_id, CAST(turn AS INTEGER) r, count(*) n, CAST(sum(length(s)) AS BIGINT) chars, CAST(sum(len(regexp_extract_all(s, '[A-Za-z]'))) AS BIGINT) letters FROM s GROUP BY 1, 2")
def dialogue_tiles(spark, d):
    return grids.dialogue(spark, d).groupBy("image_id", "r").agg(F.count("*").alias("n"), F.sum("f5").alias("chars"), F.sum("f0").alias("letters"))


@query("foreground_tiles", f"{T} SELECT {ALL} FROM tiles WHERE bg > 600")
def foreground_tiles(spark, d):
    return tiles(spark, d).filter("bg > 600")


@query("empty_tiles", f"{T} SELECT image_id, r, c FROM tiles WHERE bg = 0")
def empty_tiles(spark, d):
    return tiles(spark, d).filter("bg <=> 0").select("image_id", "r", "c")


@query("tiles_in_box", f"{T} SELECT image_id, r, c FROM tiles WHERE f0 BETWEEN 50 AND 90 AND f1 BETWEEN 60 AND 120 AND f5 IN (10, 20, 30)")
def tiles_in_box(spark, d):
    return tiles(spark, d).filter(F.col("f0").between(50, 90) & F.col("f1").between(60, 120) & F.col("f5").isin(10, 20, 30)).select("image_id", "r", "c")


@query("overlap_cells", f"{T}, a AS (SELECT image_id, dr, dc FROM (SELECT DISTINCT image_id FROM tiles), (VALUES (-1, 0), (2, 4), (5, 3)) v(dr, dc)) SELECT a.image_id, a.dr, a.dc, count(t.r) n, CAST(sum(t.bg) AS BIGINT) bg FROM a JOIN tiles t ON t.image_id = a.image_id AND t.r BETWEEN a.dr AND a.dr + 1 AND t.c BETWEEN a.dc AND a.dc + 1 GROUP BY 1, 2, 3")
def overlap_cells(spark, d):
    """Equi-join of alignments' cells with tiles on (image, row, column); shuffle hash."""
    t = tiles(spark, d)
    a = t.select("image_id").distinct().withColumn("o", F.explode(F.expr("array(struct(-1 AS dr, 0 AS dc), struct(2 AS dr, 4 AS dc), struct(5 AS dr, 3 AS dc))"))).select("image_id", "o.dr", "o.dc")
    x = a.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(3)))).select("image_id", "dr", "dc", (F.expr("CAST(i DIV 2 AS INT)") + F.col("dr")).alias("r"), (F.col("i") % 2 + F.col("dc")).alias("c"))
    return x.hint("shuffle_hash").join(t, ["image_id", "r", "c"]).groupBy("image_id", "dr", "dc").agg(F.count("*").alias("n"), F.sum("bg").alias("bg"))


@query("overhang_cells", f"{C} SELECT image_id, dr, dc, CAST(4 - count(*) AS BIGINT) missing FROM cells GROUP BY 1, 2, 3 HAVING count(*) < 4")
def overhang_cells(spark, d):
    return cells(spark, d).groupBy("image_id", "dr", "dc").agg((4 - F.count("*")).alias("missing")).filter("missing > 0")


@query("dominating_tiles", f"{T} SELECT a.image_id, count(*) n FROM tiles a JOIN tiles b ON a.image_id = b.image_id AND a.bg < b.bg AND a.r = b.r AND a.c < b.c GROUP BY 1")
def dominating_tiles(spark, d):
    t = tiles(spark, d).select("image_id", "r", "c", "bg")
    a, b = t.alias("a"), t.alias("b")
    return a.join(b, (F.col("a.image_id") == F.col("b.image_id")) & (F.col("a.r") == F.col("b.r")) & (F.col("a.bg") < F.col("b.bg")) & (F.col("a.c") < F.col("b.c"))).groupBy("a.image_id").agg(F.count("*").alias("n"))


RANGE = f"{T}, q AS (SELECT r qr, c qc, f0 x FROM tiles WHERE image_id = 3 AND r = 2) SELECT CAST(qr AS INTEGER) qr, CAST(qc AS INTEGER) qc, count(*) n FROM q JOIN tiles ON f0 BETWEEN x - 10 AND x + 10 GROUP BY 1, 2"


@query("range_pairs", RANGE)
def range_pairs(spark, d):
    """A range join as an equi-join on bins of the range's width, then an exact filter."""
    t, width = tiles(spark, d).select("image_id", "r", "c", "f0"), 20
    q = t.filter("image_id = 3 AND r = 2").select(F.col("r").alias("qr"), F.col("c").alias("qc"), F.col("f0").alias("x"))
    q = q.withColumn("bin", F.explode(F.sequence(F.floor((F.col("x") - 10) / width), F.floor((F.col("x") + 10) / width))))
    j = t.withColumn("bin", F.floor(F.col("f0") / width)).join(q, "bin").filter(F.col("f0").between(F.col("x") - 10, F.col("x") + 10))
    return j.groupBy("qr", "qc").agg(F.count("*").alias("n"))


@query("activity_asof_canvas", "WITH q AS (SELECT user_id, TIMESTAMP '2024-01-15 00:00:00' qt FROM (SELECT DISTINCT user_id FROM events)) SELECT q.user_id, max(ts) ts, max_by(event_id, (ts, event_id)) event_id FROM q JOIN events e ON e.user_id = q.user_id AND e.ts <= q.qt GROUP BY 1")
def activity_asof(spark, d):
    """As-of join: each user's last event before a time, one partial aggregation."""
    e = load(spark, d, "events", "event_id", "ts", "user_id").filter("ts <= TIMESTAMP_NTZ '2024-01-15 00:00:00'")
    return e.groupBy("user_id").agg(F.max("ts").alias("ts"), F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id"))


@query("candidate_overlaps", f"{C} SELECT DISTINCT image_id, dr, dc FROM cells WHERE dist <= 60")
def candidate_overlaps(spark, d):
    c = cells(spark, d)
    return c.select("image_id", "dr", "dc").distinct().join(c.filter("dist <= 60"), ["image_id", "dr", "dc"], "left_semi")


@query("unexplored_overlaps", f"{C}, a AS (SELECT DISTINCT image_id, dr, dc FROM cells), b AS (SELECT DISTINCT image_id, dr, dc FROM cells WHERE dist <= 200) SELECT * FROM a EXCEPT SELECT * FROM b")
def unexplored_overlaps(spark, d):
    c = cells(spark, d)
    return c.select("image_id", "dr", "dc").distinct().join(c.filter("dist <= 200"), ["image_id", "dr", "dc"], "left_anti")


@query("matrix_edges", f"{C} SELECT a.image_id, count(*) n FROM cells a JOIN cells b ON a.image_id = b.image_id AND a.dr = b.dr AND a.dc = b.dc AND a.q < b.q AND abs(a.qr - b.qr) + abs(a.qc - b.qc) = 1 GROUP BY 1")
def matrix_edges(spark, d):
    c = cells(spark, d)
    a, b = c.alias("a"), c.alias("b")
    same = [F.col(f"a.{k}") == F.col(f"b.{k}") for k in ("image_id", "dr", "dc")]
    near = F.abs(F.col("a.qr") - F.col("b.qr")) + F.abs(F.col("a.qc") - F.col("b.qc")) == 1
    return a.join(b, [*same, F.col("a.q") < F.col("b.q"), near]).groupBy("a.image_id").agg(F.count("*").alias("n"))


@query("exact_copy_docs", "SELECT md5(text) h, count(*) n, min(doc_id) first FROM documents GROUP BY 1 HAVING count(*) > 1")
def exact_copy_docs(spark, d):
    return load(spark, d, "documents", "doc_id", "text").groupBy(F.md5(F.col("text").cast("binary")).alias("h")).agg(F.count("*").alias("n"), F.min("doc_id").alias("first")).filter("n > 1")


@query("nearest_query_tile", f"WITH {cells_sql('p22')}, p AS (SELECT image_id, r, c, q, {' + '.join(f'abs(f{i} - q{i})' for i in range(6))} dist FROM tiles, qt), n AS (SELECT *, row_number() OVER (PARTITION BY image_id, r, c ORDER BY dist, q) k FROM p) SELECT image_id, r, c, q FROM n WHERE k = 1")
def nearest_query_tile(spark, d):
    """A lateral subquery measures each tile against the query's tiles; the nearest is kept."""
    t = tiles(spark, d)
    t.createOrReplaceTempView("grid_tiles")
    P.query_tiles(spark, patch(t)).createOrReplaceTempView("grid_query")
    far = " + ".join(f"abs(f{i} - q{i})" for i in range(6))
    return spark.sql(f"SELECT image_id, r, c, min_by(q, struct(far, q)) q FROM grid_tiles, LATERAL (SELECT q, {far} far FROM grid_query) n GROUP BY image_id, r, c")


@query("leaf_boxes_by_image", f"{T} SELECT image_id, CAST(min(f0) AS BIGINT) lo, CAST(max(f0) AS BIGINT) hi, count(*) n FROM tiles GROUP BY 1")
def leaf_boxes(spark, d):
    return tiles(spark, d).groupBy("image_id").agg(F.min("f0").alias("lo"), F.max("f0").alias("hi"), F.count("*").alias("n"))


@query("distinct_overlaps", f"{C} SELECT count(DISTINCT (image_id, dr, dc)) n FROM cells")
def distinct_overlaps(spark, d):
    return cells(spark, d).agg(F.count_distinct("image_id", "dr", "dc").alias("n"))


@query("tile_stats_rollup", f"{T} SELECT coalesce(image_id, -1) image_id, coalesce(r, -1) r, count(*) n, CAST(sum(bg) AS BIGINT) bg FROM tiles GROUP BY ROLLUP (image_id, r)")
def tile_stats_rollup(spark, d):
    return tiles(spark, d).rollup("image_id", "r").agg(F.count("*").alias("n"), F.sum("bg").alias("bg")).fillna(-1)


@query("tile_stats_cube", f"{T} SELECT coalesce(r, -1) r, coalesce(c, -1) c, CAST(max(bg) AS BIGINT) bg FROM tiles GROUP BY CUBE (r, c)")
def tile_stats_cube(spark, d):
    return tiles(spark, d).cube("r", "c").agg(F.max("bg").alias("bg")).fillna(-1)


@query("overlap_grouping_sets", f"{C} SELECT coalesce(image_id, -9) image_id, coalesce(dr, -9) dr, count(*) n FROM cells GROUP BY GROUPING SETS ((image_id), (dr), ())")
def overlap_grouping_sets(spark, d):
    cells(spark, d).createOrReplaceTempView("grid_cells")
    return spark.sql("SELECT image_id, dr, count(*) n FROM grid_cells GROUP BY GROUPING SETS ((image_id), (dr), ())").fillna(-9)


@query("feature_moments", f"{T} SELECT image_id, round(stddev_samp(bg), 4) sd, round(avg(bg), 4) mean, CAST(median(bg) AS DOUBLE) med, round(corr(f0, f1), 6) r01 FROM tiles GROUP BY 1")
def feature_moments(spark, d):
    return tiles(spark, d).groupBy("image_id").agg(F.round(F.stddev_samp("bg"), 4).alias("sd"), F.round(F.avg("bg"), 4).alias("mean"), F.median("bg").alias("med"), F.round(F.corr("f0", "f1"), 6).alias("r01"))


@query("best_overlap_per_image", f"{C}, s AS (SELECT image_id, dr, dc, sum(score) s FROM cells GROUP BY 1, 2, 3) SELECT image_id, CAST(max(s) AS BIGINT) s, max_by(dr, (s, -dr, -dc)) dr FROM s GROUP BY 1")
def best_overlap_per_image(spark, d):
    s = cells(spark, d).groupBy("image_id", "dr", "dc").agg(F.sum("score").alias("s"))
    return s.groupBy("image_id").agg(F.max("s").alias("s"), F.max_by("dr", F.struct("s", -F.col("dr"), -F.col("dc"))).alias("dr"))


@query("region_mask_or", f"{C} SELECT image_id, dr, dc, CAST(bit_or(1 << q) AS BIGINT) mask, bool_or(score > 0) positive FROM cells GROUP BY 1, 2, 3")
def region_mask_or(spark, d):
    bit = F.pow(F.lit(2), F.col("q")).cast("long")
    return cells(spark, d).groupBy("image_id", "dr", "dc").agg(F.bit_or(bit).alias("mask"), F.bool_or(F.col("score") > 0).alias("positive"))


@query("calendar_matrix", f"{T} SELECT image_id, r, " + ", ".join(f"CAST(max(bg) FILTER (c = {i}) AS BIGINT) c{i}" for i in range(12)) + " FROM tiles GROUP BY 1, 2")
def calendar_matrix(spark, d):
    p = tiles(spark, d).groupBy("image_id", "r").pivot("c", list(range(12))).agg(F.max("bg"))
    return p.withColumnsRenamed({str(i): f"c{i}" for i in range(12)})


@query("feature_long", f"{T} SELECT image_id, r, c, f, CAST(v AS BIGINT) v FROM (SELECT image_id, r, c, f0, f1, f2 FROM tiles) UNPIVOT (v FOR f IN (f0, f1, f2))")
def feature_long(spark, d):
    return tiles(spark, d).unpivot(["image_id", "r", "c"], ["f0", "f1", "f2"], "f", "v")


@query("rank_per_image", f"{T} SELECT image_id, r, c, CAST(rank() OVER w AS INTEGER) k, CAST(dense_rank() OVER w AS INTEGER) dk FROM tiles WINDOW w AS (PARTITION BY image_id ORDER BY bg DESC)")
def rank_per_image(spark, d):
    w = Window.partitionBy("image_id").orderBy(F.desc("bg"))
    return tiles(spark, d).select("image_id", "r", "c", F.rank().over(w).alias("k"), F.dense_rank().over(w).alias("dk"))


@query("str_slabs", f"{T} SELECT image_id, r, c, CAST(ntile(4) OVER (PARTITION BY image_id ORDER BY f0, r, c) AS INTEGER) slab FROM tiles")
def str_slabs(spark, d):
    return tiles(spark, d).select("image_id", "r", "c", F.ntile(4).over(Window.partitionBy("image_id").orderBy("f0", "r", "c")).alias("slab"))


@query("score_drop", f"{T} SELECT image_id, r, c, CAST(coalesce(bg - lag(bg) OVER w, 0) AS BIGINT) d, CAST(first_value(bg) OVER w AS BIGINT) f FROM tiles WINDOW w AS (PARTITION BY image_id ORDER BY r, c)")
def score_drop(spark, d):
    w = Window.partitionBy("image_id").orderBy("r", "c")
    return tiles(spark, d).select("image_id", "r", "c", F.coalesce(F.col("bg") - F.lag("bg").over(w), F.lit(0)).alias("d"), F.first("bg").over(w).alias("f"))


@query("row_neighbour_sums", f"{T} SELECT image_id, r, c, CAST(sum(bg) OVER (PARTITION BY image_id, r ORDER BY c ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS BIGINT) s FROM tiles")
def row_neighbour_sums(spark, d):
    w = Window.partitionBy("image_id", "r").orderBy("c").rowsBetween(-1, 1)
    return tiles(spark, d).select("image_id", "r", "c", F.sum("bg").over(w).alias("s"))


@query("topk_offset", f"{T} SELECT image_id, r, c, CAST(bg AS BIGINT) bg FROM tiles ORDER BY bg DESC, image_id, r, c LIMIT 10 OFFSET 10")
def topk_offset(spark, d):
    return tiles(spark, d).select("image_id", "r", "c", "bg").orderBy(F.desc("bg"), "image_id", "r", "c").offset(10).limit(10)


def _tops(spark, d, name="p23", **how):
    from ..search import algorithms as A

    t = tiles(spark, d)
    return A.scan(t, patch(t, name), 10, SPEC, **how).df.select("image_id", "dr", "dc")


def _top_sql(ctes):
    return f"SELECT image_id, dr, dc FROM (WITH {ctes} SELECT image_id, dr, dc, b.s s FROM best ORDER BY s DESC, image_id, dr, dc LIMIT 10)"


def _one_sweep_sql(corner):
    return f"{wide_sql('p23')}, {sweep_sql('p23', corner)}, best AS (SELECT * FROM sw_{corner})"


@query("sweep_union", f"{_top_sql(_one_sweep_sql('BL'))} UNION {_top_sql(_one_sweep_sql('TR'))}")
def sweep_union(spark, d):
    """What either of two corners' sweeps alone would rank among its ten best."""
    return _tops(spark, d, corners=("BL",)).union(_tops(spark, d, corners=("TR",))).distinct()


@query("topk_agree", f"{_top_sql(corner_sql('p23'))} INTERSECT {_top_sql(exact_sql('p23'))}")
def topk_agree(spark, d):
    """The sweeps' ten best that are also the exact solver's."""
    return _tops(spark, d).intersect(_tops(spark, d, solver="exact"))


@query("topk_missed", f"{_top_sql(exact_sql('p23'))} EXCEPT {_top_sql(_one_sweep_sql('BL'))}")
def topk_missed(spark, d):
    """The exact ten best that one corner's sweep misses."""
    return _tops(spark, d, solver="exact").exceptAll(_tops(spark, d, corners=("BL",))).distinct()


@query("topk_per_query", f"{C}, n AS (SELECT q, image_id, dr, dc, score, row_number() OVER (PARTITION BY q ORDER BY score DESC, image_id, dr, dc) k FROM cells) SELECT q, image_id, dr, dc, score FROM n WHERE k <= 3")
def topk_per_query(spark, d):
    """The three best alignments of each query tile alone."""
    w = Window.partitionBy("q").orderBy(F.desc("score"), "image_id", "dr", "dc")
    return cells(spark, d).withColumn("k", F.row_number().over(w)).filter("k <= 3").select("q", "image_id", "dr", "dc", "score")


@query("all_pair_scores", f"{C} SELECT q, count(*) n, CAST(sum(score) AS BIGINT) total FROM (SELECT q, score FROM cells) GROUP BY 1")
def all_pair_scores(spark, d):
    """Every tile with every query tile: a nested-loop join with the query's few rows broadcast."""
    return cells(spark, d).groupBy("q").agg(F.count("*").alias("n"), F.sum("score").alias("total"))


@query("score_matrix_rows", f"{C} SELECT image_id, dr, dc, array_to_string(list(score ORDER BY q), ',') scores FROM cells GROUP BY 1, 2, 3")
def score_matrix_rows(spark, d):
    """Score matrices as lists in query order."""
    g = cells(spark, d).groupBy("image_id", "dr", "dc").agg(F.array_sort(F.collect_list(F.struct("q", "score"))).alias("x"))
    return g.select("image_id", "dr", "dc", F.array_join(F.transform("x", lambda e: e["score"].cast("string")), ",").alias("scores"))


@query("precision_cube", f"{C}, h AS (SELECT q, CASE WHEN score >= 0 THEN 'yes' ELSE 'no' END hit, image_id % 2 half, score FROM cells) SELECT coalesce(CAST(q AS VARCHAR), 'all') q, coalesce(CAST(half AS VARCHAR), 'all') half, CAST(sum(CASE WHEN hit = 'yes' THEN 1 ELSE 0 END) AS BIGINT) hits, count(*) n FROM h GROUP BY CUBE (q, half)")
def precision_cube(spark, d):
    """Positive cells by query tile and half of the images, with all totals."""
    h = cells(spark, d).select("q", (F.col("image_id") % 2).alias("half"), (F.col("score") >= 0).cast("long").alias("hit"))
    g = h.cube("q", "half").agg(F.sum("hit").alias("hits"), F.count("*").alias("n"))
    return g.select(F.coalesce(F.col("q").cast("string"), F.lit("all")).alias("q"), F.coalesce(F.col("half").cast("string"), F.lit("all")).alias("half"), "hits", "n")


def recursed(spark, sql: str):
    """Saved rows of a recursive query.  Spark ends those of over a million rows with an error; here
    the data and the depth bound them, so that limit is off while they are made."""
    key = "spark.sql.cteRecursionRowLimit"
    before = spark.conf.get(key)
    spark.conf.set(key, "-1")
    try:
        return saved(spark.sql(sql))
    finally:
        spark.conf.set(key, before)


@query("sweep_recursive", f"WITH {cells_sql('p13')}, f AS (SELECT image_id, dr, dc, max(score) FILTER (q = 0) a, max(score) FILTER (q = 1) b, max(score) FILTER (q = 2) e FROM cells WHERE dr = 0 AND dc BETWEEN 0 AND 9 GROUP BY 1, 2, 3) SELECT image_id, dc, CAST(greatest(a, b + greatest(a, 0), e + greatest(b + greatest(a, 0), 0)) AS BIGINT) score FROM f")
def sweep_recursive(spark, d):
    """One sweep along a row as a recursive query: the best run that ends at each cell."""
    t = tiles(spark, d)
    c = P.cells(t, P.query_tiles(spark, patch(t, "p13")), SPEC).filter("dr = 0 AND dc BETWEEN 0 AND 9")
    saved(c.select("image_id", "dc", "q", "score")).createOrReplaceTempView("grid_row_cells")
    return recursed(
        spark,
        """WITH RECURSIVE run(image_id, dc, q, ends) AS (
             SELECT image_id, dc, q, score FROM grid_row_cells WHERE q = 0
             UNION ALL
             SELECT c.image_id, c.dc, c.q, c.score + greatest(r.ends, 0) FROM run r JOIN grid_row_cells c ON c.image_id = r.image_id AND c.dc = r.dc AND c.q = r.q + 1)
           SELECT image_id, dc, max(ends) score FROM run GROUP BY image_id, dc""",
    )


@query("above_average_tiles", f"{T} SELECT image_id, r, c FROM tiles t WHERE bg > (SELECT 1.5 * avg(bg) FROM tiles u WHERE u.image_id = t.image_id)")
def above_average(spark, d):
    tiles(spark, d).createOrReplaceTempView("grid_tiles")
    return spark.sql("SELECT image_id, r, c FROM grid_tiles t WHERE bg > (SELECT 1.5 * avg(bg) FROM grid_tiles u WHERE u.image_id = t.image_id)")


@query("images_with_foreground", "SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s_suppkey AND l_quantity >= 50)")
def images_with_foreground(spark, d):
    register(spark, d, ("supplier", "lineitem"))
    return spark.sql("SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s_suppkey AND l_quantity >= 50)")


FLOOD = f"""WITH RECURSIVE {TILES}, m AS (SELECT image_id, CAST(r * 4 + c AS INTEGER) i FROM tiles WHERE r < 3 AND c < 4 AND bg >= 300),
f AS (SELECT image_id, i FROM m WHERE i = 0 UNION SELECT m.image_id, m.i FROM f JOIN m ON m.image_id = f.image_id AND (abs(m.i - f.i) = 4 OR (abs(m.i - f.i) = 1 AND m.i // 4 = f.i // 4))) SELECT image_id, i FROM f"""


@query("flood_fill_region", FLOOD)
def flood_fill(spark, d):
    """The 4-connected part of each image's first 3 x 4 cells of some foreground that holds cell 0
    (recursive query: a row an image and step, no more steps than cells)."""
    bit = F.sum(F.expr("shiftleft(1L, r * 4 + c)"))
    m = tiles(spark, d).filter("r < 3 AND c < 4 AND bg >= 300").groupBy("image_id").agg(bit.alias("m"))
    saved(m.filter("m & 1 = 1")).createOrReplaceTempView("grid_masks")
    spread = "(seen | shiftleft(seen & 1911, 1) | shiftright(seen & 3822, 1) | shiftleft(seen, 4) | shiftright(seen, 4)) & m"  # 1911: no last column, 3822: no first
    grown = recursed(spark, f"WITH RECURSIVE f(image_id, m, seen) AS (SELECT image_id, m, 1L FROM grid_masks UNION ALL SELECT image_id, m, {spread} FROM f WHERE {spread} <> seen) SELECT image_id, bit_or(seen) seen FROM f GROUP BY image_id")
    return grown.select("image_id", "seen", F.explode(F.sequence(F.lit(0), F.lit(11))).alias("i")).filter(F.getbit("seen", F.col("i")) == 1).select("image_id", "i")


@query("activity_props", "SELECT user_id, count(json_extract_string(props, '$.k')) n, count(DISTINCT json_extract_string(props, '$.k')) kinds FROM events GROUP BY 1")
def activity_props(spark, d):
    e = load(spark, d, "events", "user_id", "props").withColumn("k", F.get_json_object("props", "$.k"))
    return e.groupBy("user_id").agg(F.count("k").alias("n"), F.count_distinct("k").alias("kinds"))


@query("overlap_bounds", f"{C} SELECT image_id, dr, dc, count(*) n, CAST(sum(greatest(score, 0)) AS BIGINT) up, max(score) top FROM cells GROUP BY 1, 2, 3")
def overlap_bounds(spark, d):
    up = F.sum(F.greatest("score", F.lit(0))).cast("long")
    return cells(spark, d).groupBy("image_id", "dr", "dc").agg(F.count("*").alias("n"), up.alias("up"), F.max(F.col("score").cast("long")).alias("top"))


@query("nearest_tile", f"{C} SELECT q, min(dist) dist, CAST(arg_min(image_id, (dist, image_id, dr, dc)) AS BIGINT) image_id FROM cells GROUP BY 1")
def nearest_tile(spark, d):
    order = F.struct("dist", "image_id", "dr", "dc")
    return cells(spark, d).groupBy("q").agg(F.min(F.col("dist").cast("long")).alias("dist"), F.min_by("image_id", order).cast("long").alias("image_id"))


@query("last_seen_score", f"{C}, o AS (SELECT q, score, row_number() OVER (PARTITION BY q ORDER BY dist, image_id, dr, dc) n FROM cells) SELECT q, max(score) FILTER (n = 8) score FROM o GROUP BY 1")
def last_seen_score(spark, d):
    order = Window.partitionBy("q").orderBy("dist", "image_id", "dr", "dc")
    seen = cells(spark, d).withColumn("n", F.row_number().over(order)).filter("n <= 8")
    return seen.groupBy("q").agg(F.max(F.when(F.col("n") == 8, F.col("score"))).cast("long").alias("score"))


@query("feature_covariance", f"{T} SELECT " + ", ".join(f"round(covar_pop(f{i}, f{j}), 3) v{i}{j}" for i in range(3) for j in range(i, 3)) + " FROM tiles")
def feature_covariance(spark, d):
    return tiles(spark, d).agg(*(F.round(F.covar_pop(f"f{i}", f"f{j}"), 3).alias(f"v{i}{j}") for i in range(3) for j in range(i, 3)))


@query("query_size_sweep", f"{T}, n AS (SELECT image_id, max(r) + 1 a, max(c) + 1 b FROM tiles GROUP BY 1) SELECT h, w, CAST(sum((a + h - 1) * (b + w - 1)) AS BIGINT) AS n_overlaps FROM n, (VALUES (2, 5), (4, 5), (5, 6), (4, 10)) q(h, w) GROUP BY 1, 2")
def query_size_sweep(spark, d):
    """Region problems that a scan solves for each query size of the sweep."""
    shape = tiles(spark, d).groupBy("image_id").agg((F.max("r") + 1).alias("a"), (F.max("c") + 1).alias("b"))
    sizes = F.explode(F.array(*(F.struct(F.lit(h).alias("h"), F.lit(w).alias("w")) for h, w in ((2, 5), (4, 5), (5, 6), (4, 10)))))
    swept = shape.select("a", "b", sizes.alias("q")).select("a", "b", "q.h", "q.w")
    return swept.groupBy("h", "w").agg(F.sum((F.col("a") + F.col("h") - 1) * (F.col("b") + F.col("w") - 1)).cast("long").alias("n_overlaps"))
