"""Quality rules as a bitmask ledger, in native columns only.

``ledger`` evaluates every rule once per document and stores the measurements
and one bit per failed rule.  Policies are versioned masks over these bits, so a
new policy, or the ablation of a rule, reads the ledger and no text.

Words are runs outside 0x20 and 0x09-0x0D.  Repeated words are those covered by
windows of three words found twice or more in the text.  Windows are compared by
64-bit hashes.

Defined results: a null or blank text has zero of everything, fails MIN_WORDS and no
ratio rule; null ids and repeated rows pass through; an empty table gives no
rows; other columns are kept by ``apply_policy`` only if the ledger has them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLANKS = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"

#: Rule name -> (bit, failing condition over the measurements).
RULES: dict[str, tuple[int, str]] = {
    "min_words": (0, "n_words < 50"),
    "repetition": (1, "100 * n_repeat_words > 50 * n_words"),
    "symbols": (2, "100 * n_symbols > 40 * n_words"),
    "duplicate_lines": (3, "100 * n_dup_lines > 60 * n_lines"),
    "long_words": (4, "word_chars > 20 * n_words"),
    "short_words": (5, "word_chars < 2 * n_words"),
}

#: Policy version -> rules whose failure rejects a document.
POLICIES: dict[int, tuple[str, ...]] = {
    1: ("min_words", "repetition"),
    2: ("min_words", "repetition", "symbols", "duplicate_lines", "long_words", "short_words"),
}
LATEST = 2


def mask(rules: tuple[str, ...]) -> int:
    return sum(1 << RULES[r][0] for r in rules)


def _without(text: Column, chars: str) -> Column:
    return F.length(F.translate(text, chars, ""))


def _let(value: Column, use) -> Column:
    """``use(value)`` with value computed once, wherever the optimizer moves the expression."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _windows(w: Column) -> Column:
    """(hash, place) of every three consecutive words, in hash order, so that equal ones are neighbours."""
    at = lambda i: F.struct(F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)).alias("h"), i.alias("p"))
    return F.sort_array(F.when(F.size(w) >= 3, F.transform(F.sequence(F.lit(0), F.size(w) - 3), at)).otherwise(F.array().cast("array<struct<h:bigint,p:int>>")))


def _covered(places: Column) -> Column:
    """Words under windows of three at ascending places."""
    start = F.struct(F.lit(-1).alias("last"), F.lit(0).alias("n"))
    return F.aggregate(places, start, lambda acc, p: F.struct((p + 2).alias("last"), (acc["n"] + F.least(F.lit(3), p + 2 - acc["last"])).alias("n")), lambda acc: acc["n"])


def _repeated(w: Column) -> Column:
    twice = lambda s: F.filter(s, lambda x, i: (F.get(s, i - 1)["h"] == x["h"]) | (F.get(s, i + 1)["h"] == x["h"]))
    return _let(_windows(w), lambda s: _covered(F.sort_array(F.transform(twice(s), lambda x: x["p"]))))


def measure(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` and the base measurements (long)."""
    body = F.coalesce(F.col(text), F.lit(""))
    words = F.regexp_extract_all(body, F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))
    lines = F.filter(F.split(body, "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    of_words = _let(words, lambda w: F.struct(F.size(w).cast("long").alias("n_words"), _repeated(w).cast("long").alias("n_repeat_words")))
    of_lines = _let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines")))
    out = docs.withColumns({"_w": of_words, "_l": of_lines, "word_chars": _without(body, BLANKS).cast("long"), "n_symbols": (F.length(body) - _without(body, SYMBOLS)).cast("long")})
    return out.withColumns({c: F.col(f"{g}.{c}") for g, c in (("_w", "n_words"), ("_w", "n_repeat_words"), ("_l", "n_lines"), ("_l", "n_dup_lines"))}).drop("_w", "_l")


MEASURES = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words")


def ledger(docs: DataFrame) -> DataFrame:
    """(doc_id, measurements, failed): one bit in ``failed`` for each rule a document fails."""
    bits = None
    for bit, rule in RULES.values():
        one = F.when(F.expr(rule), F.lit(1 << bit)).otherwise(0).cast("long")
        bits = one if bits is None else bits.bitwiseOR(one)
    return measure(docs.select("doc_id", "text")).select("doc_id", *MEASURES).withColumn("failed", bits)


def apply_policy(book: DataFrame, version: int = LATEST) -> DataFrame:
    """``kept``: no rule of the policy failed."""
    return book.withColumn("kept", F.col("failed").bitwiseAND(F.lit(mask(POLICIES[version]))) == 0)


def ablation(book: DataFrame, version: int = LATEST) -> DataFrame:
    """(rule, n_failed, n_only): documents each rule fails, and those that it alone rejects; one pass over the ledger."""
    whole = mask(POLICIES[version])
    rows = book.select(F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.lit(1 << RULES[r][0]).cast("long").alias("bit")) for r in POLICIES[version]])).alias("x"), F.col("failed").bitwiseAND(F.lit(whole)).alias("f"))
    return rows.groupBy("x.rule").agg(F.sum((F.col("f").bitwiseAND(F.col("x.bit")) != 0).cast("long")).alias("n_failed"), F.sum((F.col("f") == F.col("x.bit")).cast("long")).alias("n_only"))
