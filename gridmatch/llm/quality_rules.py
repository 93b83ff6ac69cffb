"""Quality rules as a bitmask ledger.

Every rule is measured once per document.  The ledger keeps the measurements and one bit per
failed rule; policies are versioned sets of bits, so a new policy, or the ablation of a rule,
is bitwise arithmetic on the ledger and never reads a text again.  Everything is built from
DataFrame functions: one narrow pass over the texts and no shuffle of them.

Null texts are empty (0 words, base rules failed); null or repeated ids and extra columns pass
through `ledger` untouched; an empty table gives an empty ledger.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

WS = r"[\x20\x09-\x0D]+"
SPACES = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class Rule:
    """`fails` is a SQL condition over the measurement columns."""

    bit: int
    name: str
    fails: str


#: The first two are the base rules; the others reject only texts far outside prose.
RULES = (
    Rule(0, "too_few_words", "n_words < 50"),
    Rule(1, "repeated_windows", "100 * n_repeat_words > 50 * n_words"),
    Rule(2, "symbol_heavy", "10 * n_symbols > 3 * word_chars"),
    Rule(3, "repeated_lines", "n_lines > 3 and 100 * n_dup_lines > 60 * n_lines"),
    Rule(4, "short_words", "10 * word_chars < 15 * n_words"),
    Rule(5, "long_words", "word_chars > 25 * n_words"),
)
BASE = 0b11


@dataclass(frozen=True)
class Policy:
    version: str
    mask: int


POLICIES = (Policy("base-1", BASE), Policy("prose-1", 0b111111), Policy("prose-2", 0b101111))
CURRENT = POLICIES[1]


def _repeat_words(words: Column, n: Column) -> Column:
    """Words inside three-word windows that occur twice or more.

    Windows are hashed to 64 bits with their place, sorted, and compared with their
    neighbours; the places found are then sorted and their union is measured: n log n in one
    row, whatever the text's length."""
    windows = F.when(
        n >= 3,
        F.array_sort(F.transform(F.sequence(F.lit(0), (n - 3).cast("int")), lambda j: F.struct(F.xxhash64(F.get(words, j), F.get(words, j + 1), F.get(words, j + 2)).alias("h"), j.alias("j")))),
    )
    return windows


def measurements(df: DataFrame, text: str = "text") -> DataFrame:
    """`df` with n_words, word_chars, n_symbols, n_lines, n_dup_lines and n_repeat_words (long)."""
    t = F.coalesce(F.col(text), F.lit(""))
    df = df.withColumn("_words", F.filter(F.split(t, WS), lambda w: w != ""))
    df = df.withColumn("n_words", F.size("_words").cast("long"))
    df = df.withColumn("word_chars", F.length(F.translate(t, SPACES, "")).cast("long"))
    df = df.withColumn("n_symbols", (F.length(t) - F.length(F.translate(t, SYMBOLS, ""))).cast("long"))
    df = df.withColumn("_lines", F.filter(F.split(t, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    df = df.withColumn("n_lines", F.size("_lines").cast("long")).withColumn("n_dup_lines", (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"))
    df = df.withColumn("_windows", _repeat_words(F.col("_words"), F.col("n_words")))
    s = F.col("_windows")
    same = lambda a, b: F.coalesce(a["h"] == b["h"], F.lit(False))
    at = F.filter(F.transform(s, lambda x, i: F.when(same(x, F.get(s, i - 1)) | same(x, F.get(s, i + 1)), x["j"])), lambda j: j.isNotNull())
    df = df.withColumn("_at", F.array_sort(at))
    p = F.col("_at")
    cover = F.aggregate(F.transform(p, lambda j, i: F.least(F.lit(3), j - F.coalesce(F.get(p, i - 1), j - 3))), F.lit(0), lambda a, x: a + x)
    return df.withColumn("n_repeat_words", F.coalesce(cover, F.lit(0)).cast("long")).drop("_words", "_lines", "_windows", "_at")


def ledger(df: DataFrame, rules: tuple[Rule, ...] = RULES, text: str = "text") -> DataFrame:
    """Measurements and `fail_bits`; the text goes."""
    bits = F.lit(0).cast("long")
    for r in rules:
        bits = bits + F.when(F.expr(r.fails), F.lit(1 << r.bit)).otherwise(F.lit(0)).cast("long")
    return measurements(df, text).withColumn("fail_bits", bits).drop(text)


def verdict(bits: Column, policy: Policy = CURRENT) -> Column:
    return bits.bitwiseAND(F.lit(policy.mask)) == 0


def apply_policies(led: DataFrame, policies: tuple[Policy, ...] = POLICIES) -> DataFrame:
    """The ledger with one boolean `kept_<version>` for each policy."""
    return led.withColumns({f"kept_{p.version}": verdict(F.col("fail_bits"), p) for p in policies})


def ablations(led: DataFrame, policy: Policy = CURRENT, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """For each rule of the policy: documents that fail it, that fail it alone (so that dropping
    the rule would bring them back), and what the policy keeps without it.

    The ledger is first counted by bitmask, so at most 2**rules rows meet the rule list."""
    counts = led.groupBy("fail_bits").count()
    own = [r for r in rules if policy.mask >> r.bit & 1]
    per = F.explode(F.array(*[F.struct(F.lit(r.name).alias("rule"), F.lit(1 << r.bit).cast("long").alias("mask")) for r in own])).alias("r")
    b = F.col("fail_bits").bitwiseAND(F.lit(policy.mask))
    flat = counts.select("fail_bits", "count", per).select("count", "r.rule", b.alias("b"), F.col("r.mask").alias("m"))
    pick = lambda cond: F.sum(F.when(cond, F.col("count")).otherwise(0))
    return flat.groupBy("rule").agg(pick(F.col("b").bitwiseAND(F.col("m")) != 0).alias("n_failed"), pick(F.col("b") == F.col("m")).alias("n_failed_alone"), pick((F.col("b") == 0) | (F.col("b") == F.col("m"))).alias("n_kept_without"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    led = ledger(table(spark, sf_dir, "documents").select("doc_id", "text"))
    failed = F.col("fail_bits").bitwiseAND(F.lit(BASE)) != 0
    return led.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), verdict(F.col("fail_bits")).alias("kept"), "fail_bits")


ORACLE = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') t FROM documents),
w AS (SELECT doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') ws,
        list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) ls FROM d),
g AS (SELECT doc_id, unnest(range(1, len(ws) - 1)) j, ws FROM w WHERE len(ws) >= 3),
g2 AS (SELECT doc_id, j, ws[j] a, ws[j + 1] b, ws[j + 2] c FROM g),
g3 AS (SELECT doc_id, j, count(*) OVER (PARTITION BY doc_id, a, b, c) n FROM g2),
r AS (SELECT doc_id, CAST(count(DISTINCT j + k) AS BIGINT) n FROM g3, (SELECT unnest([0, 1, 2]) k) WHERE n > 1 GROUP BY 1),
m AS (SELECT w.doc_id, CAST(len(ws) AS BIGINT) n_words,
        CAST(length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g')) AS BIGINT) word_chars,
        CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) n_symbols,
        CAST(len(ls) AS BIGINT) n_lines, CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) n_dup_lines,
        coalesce(r.n, 0) n_repeat_words FROM w LEFT JOIN r ON r.doc_id = w.doc_id),
b AS (SELECT *, CAST(CASE WHEN n_words < 50 THEN 1 ELSE 0 END
        + CASE WHEN 100 * n_repeat_words > 50 * n_words THEN 2 ELSE 0 END
        + CASE WHEN 10 * n_symbols > 3 * word_chars THEN 4 ELSE 0 END
        + CASE WHEN n_lines > 3 AND 100 * n_dup_lines > 60 * n_lines THEN 8 ELSE 0 END
        + CASE WHEN 10 * word_chars < 15 * n_words THEN 16 ELSE 0 END
        + CASE WHEN word_chars > 25 * n_words THEN 32 ELSE 0 END AS BIGINT) fail_bits FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  (fail_bits & 3) <> 0 AS base_failed, fail_bits = 0 AS kept, fail_bits FROM b
"""

QUERIES = {"op3_quality_rules": op3_quality_rules}
ORACLES = {"op3_quality_rules": ORACLE}
