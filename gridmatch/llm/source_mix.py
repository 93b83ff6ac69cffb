"""Mixing sources to target weights along a curriculum.

Targets: sources, in code-point order, get weights and share all words in proportion; a source
stops at `most` times its own size and the excess goes to the others by weight.  That fixed
point is found in closed form: sorted by size over weight, the full sources are a prefix.

Order: each source has a weight schedule over training time.  Its integral, scaled to the
source's target, is the demand for the source's words by then; a document copy stands where
that demand reaches the middle of its words.  Copies of all sources are then range-sorted by
that position.  Within a source, documents follow a hash of their id; words before a document
are summed in two steps (hash bucket, then place in the bucket), so a source that holds a third
of all rows is spread over `BUCKETS` groups.

A null source is one source, the last; a null text has no words and is taken 0 times; a null
or repeated id is placed like any other row (equal rows are interchangeable).  The document at
the end of a target is cut there, so a source's words taken are its target rounded to one word.
An empty table gives an empty mix.  Extra columns stay with the documents.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table, word_count

BUCKETS = 4096


@dataclass(frozen=True)
class Schedule:
    """Piecewise linear weight over training time 0..1; only its shape counts."""

    knots: tuple[tuple[float, float], ...] = ((0.0, 1.0), (1.0, 1.0))


#: Heavy sources rise, the middle ones stay, light ones are spent early.
CURRICULUM = (Schedule(((0.0, 0.5), (0.5, 1.0), (1.0, 1.5))), Schedule(), Schedule(((0.0, 1.5), (1.0, 0.5))))


def sizes(docs: DataFrame, carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, source, size, `carry` and the mix's order key (60 bits of a digest of the id)."""
    key = F.conv(F.substring(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), 1, 15), 16, 10).cast("long")
    return docs.select("doc_id", "source", *carry, word_count(F.col("text")).alias("size"), key.alias("key"))


def targets(per_source: DataFrame, weights: tuple[int, ...] = (5, 2, 1), most: int = 3) -> DataFrame:
    """`per_source` (source, source_size) with `slot` (place in the weight cycle) and `target`.

    One row for each source comes in; their windows are over that summary alone."""
    every = Window.partitionBy(F.lit(0))
    w = F.element_at(F.array(*map(F.lit, weights)), (F.col("slot") + 1).cast("int"))
    ranked = per_source.withColumn("slot", (F.row_number().over(every.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights))
    ranked = ranked.withColumn("w", w.cast("double")).withColumn("cap", (most * F.col("source_size")).cast("double")).withColumn("full_at", F.col("cap") / F.col("w"))
    line = every.orderBy("full_at", F.col("source").asc_nulls_last())
    before = line.rowsBetween(Window.unboundedPreceding, -1)
    left = F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))
    level = left / (F.sum("w").over(every) - F.coalesce(F.sum("w").over(before), F.lit(0.0)))
    ranked = ranked.withColumn("level", level).withColumn("place", F.row_number().over(line))
    open_level = F.min(F.when(F.col("full_at") > F.col("level"), F.struct("place", "level"))).over(every)["level"]
    target = F.when(F.col("full_at") > F.col("level"), F.col("w") * open_level).otherwise(F.col("cap"))
    return ranked.select("source", "source_size", "slot", target.alias("target"))


def _time(f: Column, schedule: Schedule) -> Column:
    """The time at which the schedule's integral has reached the share `f` of its whole."""
    pieces, total = [], 0.0
    for (t0, w0), (t1, w1) in zip(schedule.knots, schedule.knots[1:]):
        area = (t1 - t0) * (w0 + w1) / 2
        pieces.append((t0, t1, w0, w1, total, area))
        total += area
    out = F.lit(1.0)
    for t0, t1, w0, w1, done, area in reversed(pieces):
        need, slope = f * total - done, (w1 - w0) / (t1 - t0)
        inside = need / w0 if slope == 0 else (F.sqrt(F.greatest(F.lit(w0 * w0) + 2 * slope * need, F.lit(0.0))) - w0) / slope
        out = F.when(need <= area, t0 + inside).otherwise(out)
    return out


def plan(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), most: int = 3, carry: tuple[str, ...] = ()) -> DataFrame:
    """One row for each document: size, source_size, target, before (its source's words ahead of
    it), quota (the source's words in the mix), rounds (whole copies), part (words of one more
    copy), taken, slot, and the columns `carry`."""
    # a null source cannot meet itself in a join, so sources meet by a non-null form
    rows = sizes(docs, carry).withColumns({"bucket": F.shiftright("key", 60 - (BUCKETS.bit_length() - 1)), "_s": F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit(""))})
    sums = rows.groupBy("_s", "bucket").agg(F.sum("size").alias("n"))
    named = F.when(F.col("_s") != "", F.expr("substring(_s, 2)"))
    per_source = sums.groupBy("_s").agg(F.sum("n").alias("source_size")).select(named.alias("source"), "source_size")
    goals = targets(per_source, weights, most).withColumn("_s", F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit(""))).drop("source")
    ahead = Window.partitionBy("_s").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.withColumn("ahead", F.coalesce(F.sum("n").over(ahead), F.lit(0))).select("_s", "bucket", "ahead").join(goals, "_s")
    inside = Window.partitionBy("_s", "bucket").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.join(starts, ["_s", "bucket"]).withColumn("before", F.col("ahead") + F.coalesce(F.sum("size").over(inside), F.lit(0)))
    rows = rows.withColumn("quota", F.floor(F.col("target") + 0.5).cast("long"))
    rows = rows.withColumn("rounds", F.when(F.col("source_size") > 0, F.expr("quota DIV source_size")).otherwise(F.lit(0)).cast("long"))
    rest = F.col("quota") - F.col("rounds") * F.col("source_size")
    rows = rows.withColumn("part", F.greatest(F.lit(0), F.least(F.col("size"), rest - F.col("before"))).cast("long"))
    return rows.withColumn("taken", F.col("rounds") * F.col("size") + F.col("part")).drop("_s", "bucket", "ahead", "key")


def position(copy: Column, words: Column, curriculum: tuple[Schedule, ...] = CURRICULUM) -> Column:
    """Training time (0..1) of a document's copy number `copy` that holds `words` words."""
    f = (copy * F.col("source_size") + F.col("before") + words / 2) / F.greatest(F.col("quota"), F.lit(1))
    out = F.lit(0.0)
    for slot, schedule in enumerate(curriculum):
        out = F.when(F.col("slot") % len(curriculum) == slot, _time(F.least(f, F.lit(1.0)), schedule)).otherwise(out)
    return out


def training_order(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), most: int = 3, curriculum: tuple[Schedule, ...] = CURRICULUM) -> DataFrame:
    """The mix itself: the columns of `docs`, one row for each copy, with `copy` and `position`,
    range-sorted by position.  A copy cut at its target's end has its first `part` words, joined
    by single spaces.  Documents without words are not in it."""
    own = {c: f"_own_{i}" for i, c in enumerate(docs.columns)}  # their names may clash with the plan's
    carried = docs.select("doc_id", "source", "text", *[F.col(c).alias(n) for c, n in own.items() if c not in ("doc_id", "source", "text")])
    extra = tuple(n for c, n in own.items() if c not in ("doc_id", "source", "text"))
    p = plan(carried, weights, most, ("text", *extra)).filter("taken > 0")
    n = F.col("rounds") + (F.col("part") > 0).cast("long")
    p = p.withColumn("copy", F.explode(F.sequence(F.lit(0).cast("long"), n - 1)))
    words = F.when(F.col("copy") < F.col("rounds"), F.col("size")).otherwise(F.col("part"))
    p = p.withColumn("position", position(F.col("copy"), words, curriculum))
    head = F.array_join(F.expr(r"slice(filter(split(text, '[\\x20\\x09-\\x0D]+'), w -> w <> ''), 1, cast(part AS INT))"), " ")
    text = F.when((F.col("copy") < F.col("rounds")) | (F.col("part") == F.col("size")), F.col("text")).otherwise(head)
    out = p.select(*[text.alias(c) if c == "text" else F.col(c if c in ("doc_id", "source") else own[c]).alias(c) for c in docs.columns], F.col("copy").alias("_copy"), F.col("position").alias("_position"))
    return out.repartitionByRange("_position", "doc_id", "_copy").sortWithinPartitions("_position", "doc_id", "_copy")


def op1_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = plan(table(spark, sf_dir, "documents"))
    first = F.when(F.col("taken") > 0, position(F.lit(0), F.when(F.col("rounds") > 0, F.col("size")).otherwise(F.col("part")))).alias("_position")
    out = p.select("doc_id", "size", "source_size", "target", "taken", first)
    return out.repartitionByRange("_position", "doc_id").sortWithinPartitions("_position", "doc_id").drop("_position")


ORACLE = r"""
WITH d AS (SELECT doc_id, source, coalesce(CAST(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) AS BIGINT), 0) size,
    CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) key FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) source_size FROM d GROUP BY source),
k AS (SELECT *, CAST([5, 2, 1][(row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 + 1] AS DOUBLE) w, CAST(3 * source_size AS DOUBLE) cap FROM s),
l AS (SELECT *, row_number() OVER (ORDER BY cap / w, source ASC NULLS LAST) place,
    (sum(source_size) OVER () - coalesce(sum(cap) OVER (ORDER BY cap / w, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
    / (sum(w) OVER () - coalesce(sum(w) OVER (ORDER BY cap / w, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) lev FROM k),
t AS (SELECT source, source_size, CASE WHEN cap / w > lev THEN w * (SELECT arg_min(lev, place) FROM l WHERE cap / w > lev) ELSE cap END target FROM l),
q AS (SELECT d.*, t.source_size, t.target, CAST(floor(t.target + 0.5) AS BIGINT) quota,
    coalesce(CAST(sum(size) OVER (PARTITION BY d.source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT), 0) before
    FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
  CASE WHEN source_size = 0 THEN 0 ELSE (quota // source_size) * size + greatest(0, least(size, quota % source_size - before)) END taken
FROM q
"""

QUERIES = {"op1_source_mix": op1_source_mix}
ORACLES = {"op1_source_mix": ORACLE}
