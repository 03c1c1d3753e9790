"""Quality rules as a bitmask ledger.

Every rule is evaluated once on whole texts; the ledger keeps the measurements and one bit for each rule that failed. A policy is a named,
versioned set of rules: applying another one, or asking what each rule alone costs, works on the bits and never reads the text again.

Null text: no words, so all measurements are 0 and the rule on few words fails. Empty text: the same. Texts of any length are measured
whole, in O(n log n). Rows with equal ids or texts are judged each for itself; an empty table gives an empty ledger. Other columns of the
input, whatever their names, do not matter.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANK_RE, fresh

MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_letters")

#: Rule names by bit, each with its condition for failing, over the measures.
RULES: tuple[tuple[str, str], ...] = (
    ("few_words", "n_words < 50"),
    ("repeated_words", "100 * n_repeat_words > 50 * n_words"),
    ("many_symbols", "n_symbols > n_words"),
    ("repeated_lines", "n_lines > 3 AND 10 * n_dup_lines > 3 * n_lines"),
    ("word_length", "n_words > 0 AND (word_chars < 2 * n_words OR word_chars > 20 * n_words)"),
    ("shouting", "n_letters > 0 AND 10 * n_upper > 7 * n_letters"),
    ("few_letters", "2 * n_letters < word_chars"),
)

#: The rules that the stated baseline consists of.
BASE = ("few_words", "repeated_words")

#: Policies by version; a policy's rules reject, all others are only recorded.
POLICIES: dict[str, tuple[str, ...]] = {
    "base": BASE,
    "v1": tuple(name for name, _ in RULES),
    "lenient": ("few_words", "repeated_words", "many_symbols"),
}


def mask(rules) -> int:
    bits = {name: 1 << k for k, (name, _) in enumerate(RULES)}
    return sum(bits[r] for r in rules)


def ledger(docs: DataFrame, text_col: str = "text", name: str = "ledger") -> tuple[DataFrame, str]:
    """docs with one more column, a struct of MEASURES and `failures` (long: bit k set if rule k failed); and that column's name."""
    w, g, s, out = fresh(docs, "qr_words", "qr_grams", "qr_sorted", name)
    text = f"coalesce(`{text_col}`, '')"
    keep = [f"`{c}`" for c in docs.columns]
    words = docs.selectExpr(*keep, f"filter(split({text}, '{BLANK_RE}'), x -> x != '') AS `{w}`")
    grams = words.selectExpr(*keep, f"`{w}`", f"CASE WHEN size(`{w}`) < 3 THEN array() ELSE transform(sequence(0, size(`{w}`) - 3), i -> xxhash64(`{w}`[i], `{w}`[i + 1], `{w}`[i + 2])) END AS `{g}`")
    ordered = grams.selectExpr(*keep, f"`{w}`", f"CASE WHEN size(array_distinct(`{g}`)) < size(`{g}`) THEN sort_array(transform(`{g}`, (x, i) -> struct(x AS h, i AS i))) END AS `{s}`")
    found = f"array_sort(transform(filter(transform(`{s}`, (x, k) -> struct(x.i AS i, (k > 0 AND `{s}`[greatest(k - 1, 0)].h = x.h) OR (k + 1 < size(`{s}`) AND `{s}`[least(k + 1, size(`{s}`) - 1)].h = x.h) AS twice)), x -> x.twice), x -> x.i))"
    repeats, = fresh(ordered, "qr_repeats")
    at = ordered.selectExpr(*keep, f"`{w}`", f"CASE WHEN `{s}` IS NULL THEN array() ELSE {found} END AS `{repeats}`")
    lines = f"filter(split({text}, '\\n', -1), x -> x RLIKE '[^ \\\\t-\\\\r]')"
    one, = fresh(at, "qr_measures")
    measured = at.selectExpr(
        *keep,
        f"""struct(
            CAST(size(`{w}`) AS BIGINT) AS n_words,
            CAST(length(array_join(`{w}`, '')) AS BIGINT) AS word_chars,
            CAST(regexp_count({text}, '[#*$%&|<>]') AS BIGINT) AS n_symbols,
            {lines} AS lines,
            CAST(CASE WHEN size(`{repeats}`) = 0 THEN 0 ELSE 3 + aggregate(transform(`{repeats}`, (x, k) -> CASE WHEN k = 0 THEN 0 ELSE least(3, x - `{repeats}`[greatest(k - 1, 0)]) END), 0, (a, x) -> a + x) END AS BIGINT) AS n_repeat_words,
            CAST(regexp_count({text}, '\\\\p{{Lu}}') AS BIGINT) AS n_upper,
            CAST(length({text}) - length(regexp_replace({text}, '\\\\p{{L}}+', '')) AS BIGINT) AS n_letters
        ) AS `{one}`""",
    )
    m = F.col(one)
    values = {
        **{k: m[k] for k in ("n_words", "word_chars", "n_symbols", "n_repeat_words", "n_upper", "n_letters")},
        "n_lines": F.size(m["lines"]).cast("long"),
        "n_dup_lines": (F.size(m["lines"]) - F.size(F.array_distinct(m["lines"]))).cast("long"),
    }
    flat = measured.select(*[F.col(f"`{c}`") for c in docs.columns], F.struct(*[values[k].alias(k) for k in MEASURES]).alias(one))
    failures: Column = F.lit(0).cast("long")
    for bit, (_, fails) in enumerate(RULES):
        failures = failures.bitwiseOR(F.when(_over(fails, one), F.lit(1 << bit)).otherwise(F.lit(0)).cast("long"))
    return flat.select(*[F.col(f"`{c}`") for c in docs.columns], F.struct(*[F.col(one)[k].alias(k) for k in MEASURES], failures.alias("failures")).alias(out)), out


def _over(condition: str, struct_col: str) -> Column:
    """The condition with every measure read from a struct column."""
    return F.expr(re.sub("|".join(rf"\b{k}\b" for k in MEASURES), lambda m: f"`{struct_col}`.{m[0]}", condition))


def passes(failures: Column, policy: str = "v1") -> Column:
    """Whether a row of the ledger satisfies a policy."""
    return failures.bitwiseAND(F.lit(mask(POLICIES[policy]))) == 0


def apply_policy(docs: DataFrame, policy: str = "v1", text_col: str = "text") -> DataFrame:
    """The rows of docs that the policy keeps, with the columns of docs."""
    rows, name = ledger(docs, text_col)
    # A filter would be moved below the ledger's projections and evaluate them again for each measure; it stays above a column that is not deterministic.
    stop, = fresh(rows, "qr_stop")
    held = rows.withColumn(stop, F.monotonically_increasing_id())
    return held.where(passes(F.col(name)["failures"], policy) & (F.col(stop) >= 0)).select(*[F.col(f"`{c}`") for c in docs.columns])


def ablations(rows: DataFrame, failures: Column, policy: str = "v1") -> DataFrame:
    """For each rule of a policy: rows that fail it, rows that fail it alone (kept without it), rows kept under the policy. Works on at most 2^rules groups."""
    cut = F.lit(mask(POLICIES[policy]))
    classes = rows.groupBy(failures.bitwiseAND(cut).alias("bits")).agg(F.count(F.lit(1)).alias("n"))
    rules = F.array(*[F.struct(F.lit(r).alias("rule"), F.lit(mask([r])).cast("long").alias("bit")) for r in POLICIES[policy]])
    each = classes.select("bits", "n", F.explode(rules).alias("r"))
    return each.groupBy(F.col("r.rule").alias("rule")).agg(
        F.sum(F.when(F.col("bits").bitwiseAND(F.col("r.bit")) != 0, F.col("n")).otherwise(0)).alias("n_failed"),
        F.sum(F.when(F.col("bits") == F.col("r.bit"), F.col("n")).otherwise(0)).alias("n_failed_alone"),
        F.sum(F.when(F.col("bits") == 0, F.col("n")).otherwise(0)).alias("n_kept"),
    )
