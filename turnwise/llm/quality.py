"""Rule bitmask ledger: each rule runs once, policies and ablations are bit operations on what it left.

measurements() computes every number that a rule needs in one projection over the text, native expressions only and
without a shuffle: a row never leaves its task, so a hot source or a very long text costs its own size and no more.
ledger() adds failures, a long whose bit b is set if rule b fails. A policy is a named, versioned set of bits; verdict()
keeps a row if it fails none of them. ablation() counts rows by failure mask (few distinct masks, combined before the
shuffle) and derives from those counts what each policy drops, what each rule drops alone and what leaving it out keeps.

Edge cases: a null text counts as empty and has no words (all measurements 0, rule short fails); ties and repeated
rows are judged each by itself; an empty table gives an empty ledger and an ablation without counts; other columns of
the input pass through ledger() unless they have the name of one that it adds, which then gives way.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.llm.common import WORD_SPACE, stored, table, text_of


@dataclass(frozen=True)
class Rule:
    bit: int
    name: str
    fails: str  # SQL over the measurements


RULES = (
    Rule(0, "short", "n_words < 50"),
    Rule(1, "repeated_words", "100 * n_repeat_words > 50 * n_words"),
    Rule(2, "symbols", "10 * n_symbols > n_words"),
    Rule(3, "duplicate_lines", "2 * n_dup_lines > n_lines"),
    Rule(4, "short_words", "2 * word_chars < 5 * n_words"),
    Rule(5, "long_words", "word_chars > 12 * n_words"),
    Rule(6, "shouting", "10 * n_marks > 3 * n_words"),
    Rule(7, "very_long", "n_words > 100000"),
)
#: Bits that each version of a policy enforces.
POLICIES = {
    "base-1": ("short", "repeated_words"),
    "text-1": ("short", "repeated_words", "symbols", "duplicate_lines"),
    "text-2": ("short", "repeated_words", "symbols", "duplicate_lines", "short_words", "long_words", "shouting"),
    "text-3": ("short", "repeated_words", "symbols", "duplicate_lines", "short_words", "long_words", "shouting", "very_long"),
}
BASE, CURRENT = "base-1", "text-2"
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_marks")


def policy_mask(policy: str) -> int:
    bits = {r.name: r.bit for r in RULES}
    return sum(1 << bits[x] for x in POLICIES[policy])


def _repeat_words(words: str) -> list[tuple[str, Column]]:
    """Steps to the number of words in 3-word windows that occur twice or more: sort the windows' hashes with their
    places, keep the places whose neighbour has the same hash, and add up what each covers before the next begins."""
    w = F.col(words)
    windows = F.transform(F.slice(w, 1, F.greatest(F.size(w) - 2, F.lit(0))), lambda x, i: F.struct(F.xxhash64(x, F.get(w, i + 1), F.get(w, i + 2)).alias("h"), i.alias("i")))
    s, p = F.col("_sorted"), F.col("_places")
    same = lambda x, j: F.coalesce(F.get(s, j)["h"] == x["h"], F.lit(False))
    places = F.sort_array(F.transform(F.filter(s, lambda x, k: same(x, k + 1) | ((k > 0) & same(x, k - 1))), lambda x: x["i"]))
    covered = F.aggregate(F.transform(p, lambda x, k: F.least(F.lit(3), F.coalesce(F.get(p, k + 1) - x, F.lit(3)))), F.lit(0), lambda a, x: a + x)
    return [("_sorted", F.sort_array(windows)), ("_places", places), ("n_repeat_words", covered.cast("long"))]


def measurements(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with the columns of MEASURES."""
    out = docs.drop(*MEASURES, "_text", "_words", "_lines", "_sorted", "_places").withColumn("_text", text_of(text_col))
    out = out.withColumn("_words", F.array_remove(F.split("_text", WORD_SPACE, -1), "")).withColumn("_lines", F.filter(F.split("_text", "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    size = lambda c: F.length(c).cast("long")
    out = out.withColumns(
        {
            "n_words": F.size("_words").cast("long"),
            "word_chars": size(F.array_join("_words", "")),
            "n_symbols": size(F.col("_text")) - size(F.regexp_replace("_text", r"[#*$%&|<>]+", "")),
            "n_marks": size(F.col("_text")) - size(F.regexp_replace("_text", r"!+", "")),
            "n_lines": F.size("_lines").cast("long"),
            "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
        }
    )
    for name, value in _repeat_words("_words"):
        out = out.withColumn(name, value)
    return out.drop("_text", "_words", "_lines", "_sorted", "_places")


def ledger(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with the measurements and failures, the bits of all rules that fail."""
    mask = F.lit(0).cast("long")
    for r in RULES:
        mask = mask.bitwiseOR(F.when(F.expr(r.fails), F.lit(1 << r.bit)).otherwise(F.lit(0)).cast("long"))
    return measurements(docs.drop("failures"), text_col).withColumn("failures", mask)


def verdict(failures: Column, policy: str = CURRENT) -> Column:
    return failures.bitwiseAND(F.lit(policy_mask(policy))) == 0


def ablation(rows: DataFrame) -> DataFrame:
    """(policy, rule, n_rows, fails, fails_alone, kept, kept_without): for each rule of each policy, from a ledger."""
    masks = rows.groupBy("failures").agg(F.count("*").alias("n"))
    rules = [(p, r.name, policy_mask(p), 1 << r.bit) for p in POLICIES for r in RULES if r.name in POLICIES[p]]
    plan = rows.sparkSession.createDataFrame(rules, "policy string, rule string, mask long, bit long")
    count = lambda c: F.sum(F.when(c, F.col("n")).otherwise(0)).alias
    hit = lambda m: F.col("failures").bitwiseAND(m)
    return (
        masks.join(F.broadcast(plan), F.lit(True))
        .groupBy("policy", "rule")
        .agg(
            F.sum("n").alias("n_rows"),
            count(hit(F.col("bit")) != 0)("fails"),
            count(hit(F.col("mask")) == F.col("bit"))("fails_alone"),
            count(hit(F.col("mask")) == 0)("kept"),
            count(hit(F.col("mask").bitwiseXOR(F.col("bit"))) == 0)("kept_without"),
        )
    )


def op5_quality_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = ledger(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", (~verdict(F.col("failures"), BASE)).alias("base_failed"), verdict(F.col("failures")).alias("kept"), "failures")


def ablation_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ablation of every policy over all documents. The ledger is written once; policies read nothing but its bits."""
    written = stored(ledger(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("text"), "ledger")
    return ablation(written)


#: The six spaces, as DuckDB regular expressions write them.
_SPLIT = r"[\x20\x09-\x0D]+"
ORACLE = f"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, text, list_filter(regexp_split_to_array(text, '{_SPLIT}'), lambda x: x <> '') AS words,
        list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS ls FROM t),
windows AS (SELECT doc_id, unnest(range(1, len(words) - 1)) AS i, words FROM w),
keyed AS (SELECT doc_id, i, words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] AS k FROM windows),
counted AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS n FROM keyed),
covered AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM counted WHERE n > 1) GROUP BY doc_id),
m AS (SELECT w.doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(length(list_aggregate(list_concat([''], words), 'string_agg', '')) AS BIGINT) AS word_chars,
        CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
        CAST(length(text) - length(replace(text, '!', '')) AS BIGINT) AS n_marks,
        CAST(len(ls) AS BIGINT) AS n_lines, CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines, coalesce(c.n, 0) AS n_repeat_words
      FROM w LEFT JOIN covered c USING (doc_id)),
f AS (SELECT *, CAST({" + ".join(f"CASE WHEN {r.fails} THEN {1 << r.bit} ELSE 0 END" for r in RULES)} AS BIGINT) AS failures FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (failures & {policy_mask(BASE)}) <> 0 AS base_failed,
  (failures & {policy_mask(CURRENT)}) = 0 AS kept, failures FROM f
"""
_PLANNED = " UNION ALL ".join(f"SELECT '{p}' AS policy, '{r.name}' AS rule, {policy_mask(p)} AS mask, {1 << r.bit} AS bit" for p in POLICIES for r in RULES if r.name in POLICIES[p])
ABLATION_ORACLE = f"""
WITH rows AS ({ORACLE.strip()}), planned AS ({_PLANNED})
SELECT policy, rule, count(*) AS n_rows, count(*) FILTER ((failures & bit) <> 0) AS fails, count(*) FILTER ((failures & mask) = bit) AS fails_alone,
  count(*) FILTER ((failures & mask) = 0) AS kept, count(*) FILTER ((failures & xor(mask, bit)) = 0) AS kept_without
FROM rows, planned GROUP BY policy, rule
"""
