"""Quality rules as a bitmask ledger.

Every rule is measured once for each document; its verdict is one bit of ``fail_bits``. Policies are versioned masks over those
bits, so a new policy, or an ablation that leaves a rule out, reads the ledger and never the texts again.

Defined results: a null text counts as no words (all measures 0) and fails the word-count rule; repeated rows give repeated rows;
columns of the input other than doc_id and text are ignored, so clashing names do no harm; an empty table gives an empty ledger.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, words_sql

MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_text_lines")


@dataclass(frozen=True)
class Rule:
    """``fails`` is a SQL predicate over the measures; its verdict is stored in bit ``bit``."""

    bit: int
    name: str
    fails: str


@dataclass(frozen=True)
class Policy:
    version: str
    rules: tuple[str, ...]


RULES = (
    Rule(0, "few_words", "n_words < 50"),
    Rule(1, "repeated_windows", "100 * n_repeat_words > 50 * n_words"),
    Rule(2, "symbols", "100 * n_symbols > 30 * n_words"),
    Rule(3, "repeated_lines", "100 * n_dup_lines > 50 * n_text_lines"),
    Rule(4, "word_length", "word_chars < 2 * n_words OR word_chars > 16 * n_words"),
)
BASE = Policy("base", ("few_words", "repeated_windows"))
STRICT = Policy("v1", tuple(r.name for r in RULES))


def mask(policy: Policy, rules=RULES) -> int:
    bits = {r.name: 1 << r.bit for r in rules}
    return sum(bits[name] for name in policy.rules)


def _repeat_words_sql() -> str:
    """Words covered by windows of three words that occur twice or more, within a lambda over the word array ``w``.

    Each window becomes one long: the high bits of its hash, then its position. After a primitive sort, equal windows are
    neighbours; the words of neighbours with equal hash bits are compared, so that a collision doesn't count.
    """
    same = "(shiftright(x, b) = shiftright({y}, b) AND w[int(x & m)] = w[int({y} & m)] AND w[int(x & m) + 1] = w[int({y} & m) + 1] AND w[int(x & m) + 2] = w[int({y} & m) + 2])"
    before, after = same.format(y="s[k - 1]"), same.format(y="s[k + 1]")
    hits = f"filter(s, (x, k) -> (k > 0 AND {before}) OR (k < size(s) - 1 AND {after}))"
    cover = (
        f"aggregate(sort_array(transform({hits}, x -> x & m)), named_struct('n', 0L, 'last', -9L), "
        "(a, p) -> named_struct('n', a.n + least(3L, p - a.last), 'last', p), a -> a.n)"
    )
    windows = "sort_array(transform(sequence(0, size(w) - 3), i -> shiftleft(xxhash64(w[i], w[i + 1], w[i + 2]), b) | i))"
    bound = f"transform(array(length(bin(size(w)))), b -> transform(array({windows}), s -> transform(array(shiftleft(1L, b) - 1L), m -> {cover})[0])[0])[0]"
    return f"CASE WHEN size(w) < 4 THEN 0L ELSE {bound} END"


def measure(docs: DataFrame) -> DataFrame:
    """doc_id and the measures of every whole text; one narrow projection, no shuffle."""
    space = "' \\t\\n\\u000b\\u000c\\r'"
    by_words = (
        f"transform(array({words_sql('body')}), w -> named_struct('n_words', bigint(size(w)), "
        f"'word_chars', bigint(length(array_join(w, ''))), 'n_repeat_words', {_repeat_words_sql()}))[0]"
    )
    by_lines = (
        f"transform(array(filter(split(body, '\\n'), l -> trim(BOTH {space} FROM l) != '')), l -> named_struct("
        "'n_text_lines', bigint(size(l)), 'n_dup_lines', bigint(size(l) - size(array_distinct(l)))))[0]"
    )
    return (
        docs.select("doc_id", F.coalesce("text", F.lit("")).alias("body"))
        .select("doc_id", F.expr(by_words).alias("ww"), F.expr(by_lines).alias("ll"), F.expr("bigint(regexp_count(body, '[#*$%&|<>]'))").alias("n_symbols"))
        .select("doc_id", *(F.col(f"{'ll' if 'line' in m else 'ww'}.{m}") if m != "n_symbols" else F.col(m) for m in MEASURES))
    )


def ledger(docs: DataFrame, rules=RULES) -> DataFrame:
    """Measures and ``fail_bits`` of every document: each rule is evaluated once."""
    bits = [F.when(F.expr(r.fails), F.lit(1 << r.bit)).otherwise(F.lit(0)).cast("long") for r in rules]
    total = bits[0]
    for b in bits[1:]:
        total = total.bitwiseOR(b)
    return measure(docs).withColumn("fail_bits", total)


def apply_policy(book: DataFrame, policy: Policy, rules=RULES) -> DataFrame:
    """Adds policy_version and kept; only the stored bits are read."""
    return book.withColumn("policy_version", F.lit(policy.version)).withColumn("kept", F.col("fail_bits").bitwiseAND(F.lit(mask(policy, rules))) == 0)


def ablations(book: DataFrame, policy: Policy, rules=RULES) -> DataFrame:
    """For each rule of the policy: documents that fail it, that fail it alone (those its removal would bring back) and the kept count without it."""
    whole = mask(policy, rules)
    chosen = [r for r in rules if r.name in policy.rules]
    bits = F.col("fail_bits")
    sums = [F.count(F.lit(1)).alias("n")]
    for r in chosen:
        one = 1 << r.bit
        sums += [
            F.sum((bits.bitwiseAND(F.lit(one)) != 0).cast("long")).alias(f"f{r.bit}"),
            F.sum((bits.bitwiseAND(F.lit(whole)) == one).cast("long")).alias(f"a{r.bit}"),
            F.sum((bits.bitwiseAND(F.lit(whole & ~one)) == 0).cast("long")).alias(f"k{r.bit}"),
        ]
    one_row = book.agg(*sums)
    rows = [
        F.struct(F.lit(policy.version).alias("policy_version"), F.lit(r.name).alias("rule"), F.coalesce(f"f{r.bit}", F.lit(0)).alias("n_failed"), F.coalesce(f"a{r.bit}", F.lit(0)).alias("n_failed_alone"), F.coalesce(f"k{r.bit}", F.lit(0)).alias("n_kept_without"))
        for r in chosen
    ]
    return one_row.select(F.explode(F.array(*rows)).alias("r")).select("r.*")


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    book = apply_policy(ledger(load(spark, sf_dir, "documents")), STRICT)
    failed = F.col("fail_bits").bitwiseAND(F.lit(mask(BASE))) != 0
    return book.select("doc_id", *MEASURES[:5], failed.alias("base_failed"), "kept", "n_text_lines", "fail_bits", "policy_version")


def quality_ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ablations(ledger(load(spark, sf_dir, "documents")), STRICT)


_SQL_MEASURES = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS body FROM documents),
w AS (SELECT rid, doc_id, body, regexp_extract_all(body, '[^\x20\x09-\x0D]+') AS w FROM d),
win AS (SELECT rid, unnest(range(1, len(w) - 1)) AS i, unnest(list_transform(range(1, len(w) - 1), lambda i: w[i:i+2])) AS g FROM w WHERE len(w) >= 3),
rep AS (SELECT rid, i FROM win QUALIFY count(*) OVER (PARTITION BY rid, g) > 1),
cov AS (SELECT rid, count(DISTINCT p) AS n FROM (SELECT rid, unnest([i, i + 1, i + 2]) AS p FROM rep) GROUP BY rid),
ln AS (SELECT rid, unnest(string_split(body, chr(10))) AS l FROM d),
dup AS (SELECT rid, count(*) AS n_lines, count(*) - count(DISTINCT l) AS n FROM ln WHERE regexp_matches(l, '[^\x20\x09-\x0D]') GROUP BY rid),
m AS (SELECT w.doc_id, len(w.w)::BIGINT AS n_words, coalesce(list_sum(list_transform(w.w, lambda x: length(x))), 0)::BIGINT AS word_chars,
  len(regexp_extract_all(w.body, '[#*$%&|<>]'))::BIGINT AS n_symbols, coalesce(dup.n, 0)::BIGINT AS n_dup_lines, coalesce(cov.n, 0)::BIGINT AS n_repeat_words,
  coalesce(dup.n_lines, 0)::BIGINT AS n_text_lines FROM w LEFT JOIN cov USING (rid) LEFT JOIN dup USING (rid)),
f AS (SELECT *, n_words < 50 AS r0, 100 * n_repeat_words > 50 * n_words AS r1, 100 * n_symbols > 30 * n_words AS r2, 100 * n_dup_lines > 50 * n_text_lines AS r3,
  word_chars < 2 * n_words OR word_chars > 16 * n_words AS r4 FROM m),
b AS (SELECT *, (r0::INT + 2 * r1::INT + 4 * r2::INT + 8 * r3::INT + 16 * r4::INT)::BIGINT AS fail_bits FROM f)
"""

QUERIES = {"op1_quality_rules": op1_quality_rules, "quality_ablations": quality_ablations}
SQL = {
    "op1_quality_rules": _SQL_MEASURES
    + "SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, r0 OR r1 AS base_failed, fail_bits = 0 AS kept, n_text_lines, fail_bits, 'v1' AS policy_version FROM b",
    "quality_ablations": _SQL_MEASURES
    + "SELECT 'v1' AS policy_version, r AS rule, sum(((fail_bits & bit) != 0)::INT)::BIGINT AS n_failed, sum((fail_bits = bit)::INT)::BIGINT AS n_failed_alone, "
    "sum(((fail_bits & (31 - bit)) = 0)::INT)::BIGINT AS n_kept_without FROM b, (VALUES ('few_words', 1), ('repeated_windows', 2), ('symbols', 4), ('repeated_lines', 8), ('word_length', 16)) AS t(r, bit) GROUP BY r, bit",
}
