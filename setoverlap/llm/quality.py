"""Quality rules: a table of thresholds compiled into one projection of built-in functions (no Python on rows).

Defined cases: a null text counts as empty (no words: it fails the 50-word rule); repeated rows each get
their own row; an empty table gives an empty result; columns other than doc_id and text are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setoverlap.llm.common import fenced

SPACE = r"[\x20\x09-\x0D]+"
SYMBOLS = "#*$%&|<>"
# Frequent function words of the four languages of the corpus.
STOP_WORDS = ["the", "of", "and", "to", "in", "is", "that", "for", "der", "die", "das", "und", "ist", "mit", "von", "el", "la", "de", "que", "los", "en", "le", "les", "et", "des", "un", "une", "a", "es", "zu", "den", "y", "du", "est"]

#: (name, SQL over the measured columns, lowest value allowed, highest value allowed); None: open.
THRESHOLDS: list[tuple[str, str, float | None, float | None]] = [
    ("symbols_per_word", "n_symbols / greatest(n_words, 1)", None, 0.30),
    ("chars_per_word", "word_chars / greatest(n_words, 1)", 2.0, 16.0),
    ("capital_words", "n_capital_words / greatest(n_words, 1)", None, 0.30),
    ("duplicate_lines", "n_dup_lines / greatest(n_lines, 1)", None, 0.50),
    ("stop_words", "n_stop_words / greatest(n_words, 1)", 0.02, None),
]


def base_rule() -> Column:
    return F.expr("n_words < 50 OR 100 * n_repeat_words > 50 * n_words")


def verdict(thresholds=THRESHOLDS) -> Column:
    """One boolean expression from the table: every ratio lies within its bounds."""
    tests = []
    for _, sql, low, high in thresholds:
        tests += [f"(({sql}) >= {low}D)"] * (low is not None) + [f"(({sql}) <= {high}D)"] * (high is not None)
    return F.expr(" AND ".join(tests) or "true")


def _start_mask(n: Column) -> Column:
    """Ones in the low bits that hold any start below n."""
    return F.call_function("shiftleft", F.lit(1).cast("long"), F.ceil(F.log2(n + F.lit(2))).cast("int")) - 1


def _repeat_words(words: Column, mask: Column) -> Column:
    """Words inside 3-word windows that occur at least twice.

    A window becomes one long: hash bits above, its start in the low bits. Longs sort as primitives; neighbours
    with equal hash bits are then compared word by word, two places to each side.
    """
    n, high = F.size(words), F.bitwise_not(mask)
    packed = F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)).bitwiseAND(high).bitwiseOR(i.cast("long")))

    def windows(b: Column) -> Column:
        s = b["s"]
        near = F.filter(F.sequence(F.lit(1), F.size(s) - 1), lambda j: F.get(s, j).bitwiseXOR(F.get(s, j - 1)).bitwiseAND(high) == 0)
        return F.array_distinct(F.flatten(F.transform(near, lambda j: F.array(F.get(s, j - 1), F.get(s, j)))))

    def starts(at: Column) -> Column:
        word = lambda v, k: F.get(words, v.bitwiseAND(mask).cast("int") + k)

        def same(i: Column, j: Column) -> Column:
            return F.coalesce((word(i, 0) == word(j, 0)) & (word(i, 1) == word(j, 1)) & (word(i, 2) == word(j, 2)), F.lit(False))

        return F.filter(at, lambda i, k: same(i, F.get(at, k - 1)) | same(i, F.get(at, k + 1)) | same(i, F.get(at, k - 2)) | same(i, F.get(at, k + 2)))

    # one-element transforms bind what they hold once
    held = F.transform(F.array(F.struct(F.sort_array(packed).alias("s"))), windows)
    found = F.flatten(F.transform(held, starts))
    covered = F.array_distinct(F.flatten(F.transform(found, lambda v: F.array(v.bitwiseAND(mask), v.bitwiseAND(mask) + 1, v.bitwiseAND(mask) + 2))))
    return F.when(n < 4, F.lit(0)).otherwise(F.size(covered)).cast("long")


def measure(df: DataFrame, text: str = "text") -> DataFrame:
    """Adds q_* measures to any table with a text column."""
    t = F.coalesce(F.col(text).cast("string"), F.lit(""))
    staged = df.withColumn("q_words", F.filter(F.split(t, SPACE), lambda w: w != "")).withColumn("q_lines", F.filter(F.split(t, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))).withColumn("q_mask", _start_mask(F.size("q_words")))
    w, lines = F.col("q_words"), F.col("q_lines")
    return staged.withColumns({
        "n_words": F.size(w).cast("long"),
        "word_chars": F.length(F.array_join(w, "")).cast("long"),
        "n_symbols": (F.length(t) - F.length(F.translate(t, SYMBOLS, ""))).cast("long"),
        "n_lines": F.size(lines).cast("long"),
        "n_dup_lines": (F.size(lines) - F.size(F.array_distinct(lines))).cast("long"),
        "n_repeat_words": _repeat_words(w, F.col("q_mask")),
        "n_capital_words": F.size(F.filter(w, lambda x: ((x < "a") | (x > "~")) & x.rlike(r"^\p{Lu}{3,}"))).cast("long"),
        "n_stop_words": F.size(F.filter(w, lambda x: x.isin(STOP_WORDS))).cast("long"),
    }).drop("q_words", "q_lines", "q_mask")


def quality_rules(df: DataFrame, thresholds=THRESHOLDS) -> DataFrame:
    """One row a document: the measures, base_failed and kept."""
    m = measure(df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text")))
    m = m.withColumn("base_failed", base_rule())
    return fenced(m.withColumn("kept", ~F.col("base_failed") & verdict(thresholds)).drop("text", "n_lines"))


def keep_good(df: DataFrame) -> DataFrame:
    """The rows of df, all columns as they are, that pass the rules."""
    names = df.columns
    inner = measure(df.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("q_row"), F.col("text")))
    return fenced(inner).where(~base_rule() & verdict()).select("q_row.*")


_W = r"[^\x20\x09-\x0D]+"
ORACLE = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, regexp_extract_all(t, '{_W}') AS ws, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '{_W}')) AS ls FROM d),
g AS (SELECT doc_id, i, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2] AS g FROM w, unnest(range(1, len(ws) - 1)) AS u(i)),
r AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS c FROM g) WHERE c > 1),
c AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM r, unnest([0, 1, 2]) AS u(k) GROUP BY doc_id),
m AS (SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::BIGINT AS word_chars,
  (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
  (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, len(ls) AS n_lines, coalesce(c.n, 0)::BIGINT AS n_repeat_words,
  len(list_filter(ws, lambda x: regexp_matches(x, '^\p{{Lu}}{{3,}}')))::BIGINT AS n_capital_words,
  len(list_filter(ws, lambda x: list_contains([{', '.join(repr(x) for x in STOP_WORDS)}], x)))::BIGINT AS n_stop_words
  FROM w LEFT JOIN c ON w.doc_id = c.doc_id),
b AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_capital_words, n_stop_words, base_failed,
  NOT base_failed AND n_symbols <= 0.30 * n_words AND word_chars >= 2.0 * n_words AND word_chars <= 16.0 * n_words
  AND n_capital_words <= 0.30 * n_words AND n_dup_lines <= 0.50 * n_lines AND n_stop_words >= 0.02 * n_words AS kept FROM b
"""
