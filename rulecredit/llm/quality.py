"""Quality rules: one threshold table compiled into one Spark projection.

Every rule is a row ``(measure, comparison, bound, min_words)`` of
:data:`RULES`; :func:`apply_quality_rules` turns the whole table into column
expressions over a handful of shared measures, so a pass is one scan without
a shuffle, a join or a user function.

Defined results: a null or blank text has no words, fails the base rule and is
rejected; ties and repeated rows are judged alike, each on its own text, whatever its id; a very
long text is one row of one task; an empty table gives an empty result. :func:`apply_quality_rules`
replaces columns named like a measure and drops those named like a working column (``_words``, ``_n``,
``_dense``, ``_keys``, ``_tagged``, ``_lines``); :func:`kept_documents` passes all columns on.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, symbol characters, stop words of four languages.
SPACES = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
STOP_WORDS = (
    "a an and are as at be by for from has have he in is it of on or that the this to was were will with "
    "au aux avec ce dans de des du elle en est et il la le les pas par pour qui que sur un une "
    "auf das dem den der des die ein eine es für im ist mit nicht sich sie und von zu "
    "al como con del el ella ellos es esta la las los no para por que se su un una y"
).split()


@dataclass(frozen=True)
class Rule:
    """A document is rejected when ``measure <op> bound`` and it has at least ``min_words`` words."""

    measure: str
    op: str
    bound: float
    min_words: int = 0


#: The threshold table. Ratios are per word unless the measure says otherwise.
RULES = (
    Rule("n_words", "<", 10),
    Rule("repeat_ratio", ">", 0.20),
    Rule("symbol_ratio", ">", 0.10),
    Rule("mean_word_chars", "<", 2.5),
    Rule("mean_word_chars", ">", 12.0),
    Rule("stop_ratio", "<", 0.02, 40),
    Rule("bang_ratio", ">", 0.30),
    Rule("no_letter_ratio", ">", 0.40),
    Rule("dup_line_ratio", ">", 0.50, 40),
)
BASE = RULES[:2]


def _occurrence_cover(words: Column, n: Column, width: int) -> Column:
    """Words inside a ``width``-word window whose sequence occurs twice or more.

    Windows are keyed by a 64-bit hash of their words. Only texts with a repeated
    key are sorted; covered words follow from the gaps between sorted starts.
    """
    last = n - width + 1
    keys = F.transform(
        F.sequence(F.lit(0), last - 1),
        lambda i: F.xxhash64(*[F.get(words, i + j) for j in range(width)]),
    )
    return F.when(n >= width, keys).otherwise(F.array().cast("array<bigint>"))


def _repeat_starts(tagged: Column) -> Column:
    """Sorted starts of the windows whose key has an equal neighbour in ``tagged``."""
    hits = F.filter(
        tagged,
        lambda e, j: F.coalesce(F.get(tagged, j - 1)["k"] == e["k"], F.lit(False))
        | F.coalesce(F.get(tagged, j + 1)["k"] == e["k"], F.lit(False)),
    )
    return F.array_sort(F.transform(hits, lambda e: e["i"]))


def _covered(starts: Column, width: int) -> Column:
    """Positions covered by ``width``-long windows at the sorted ``starts``."""
    return F.aggregate(
        starts,
        F.struct(F.lit(0).cast("bigint").alias("n"), F.lit(-width).cast("int").alias("p")),
        lambda acc, s: F.struct(
            (acc["n"] + F.least(F.lit(width), s - acc["p"])).cast("bigint").alias("n"), s.alias("p")
        ),
        lambda acc: acc["n"],
    )


def measures(docs: DataFrame, text: str = "text", window: int = 5) -> DataFrame:
    """Add the word, symbol, line and repetition counts the rule table uses."""
    t = F.coalesce(F.col(text), F.lit(""))
    blank = F.array().cast("array<string>")
    trimmed = F.btrim(t, F.lit(SPACES))
    out = docs.withColumn("_words", F.when(trimmed == "", blank).otherwise(F.split(trimmed, r"[\x20\x09-\x0D]+")))
    w = F.col("_words")
    dense = F.translate(t, SPACES, "")
    out = out.withColumn("_dense", dense).withColumn("_n", F.size(w))
    out = out.withColumn("_keys", _occurrence_cover(w, F.col("_n"), window))
    keys = F.col("_keys")
    pairs = F.array_sort(F.transform(keys, lambda k, i: F.struct(k.alias("k"), i.alias("i"))))
    none = F.slice(F.transform(keys, lambda k, i: F.struct(k.alias("k"), i.alias("i"))), 1, 0)
    once = F.size(F.array_distinct(keys)) == F.size(keys)
    out = out.withColumn("_tagged", F.when(once, none).otherwise(pairs))
    lines = F.filter(F.split(t, "\n"), lambda x: F.btrim(x, F.lit(SPACES)) != "")
    out = out.withColumn("_lines", lines)
    stop = F.size(F.filter(w, lambda x: F.lower(x).isin(STOP_WORDS)))
    bang = F.size(F.filter(w, lambda x: x.endswith("!!")))
    bare = F.size(F.filter(w, lambda x: ~x.rlike(r"[\p{L}\p{N}]")))
    n_lines = F.size("_lines").cast("bigint")
    return (
        out.withColumn("n_words", F.col("_n").cast("bigint"))
        .withColumn("word_chars", F.length("_dense").cast("bigint"))
        .withColumn("n_symbols", (F.length("_dense") - F.length(F.translate("_dense", SYMBOLS, ""))).cast("bigint"))
        .withColumn("n_lines", n_lines)
        .withColumn("n_dup_lines", n_lines - F.size(F.array_distinct("_lines")))
        .withColumn(
            "n_repeat_words",
            _covered(_repeat_starts(F.col("_tagged")), window),
        )
        .withColumn("n_stop_words", stop.cast("bigint"))
        .withColumn("n_bang_words", bang.cast("bigint"))
        .withColumn("n_bare_words", bare.cast("bigint"))
        .drop("_words", "_dense", "_n", "_keys", "_tagged", "_lines")
    )


def _measure(name: str) -> tuple[Column, Column]:
    """Numerator and denominator, so that bounds compare without dividing."""
    one = F.lit(1).cast("bigint")
    return {
        "n_words": (F.col("n_words"), one),
        "repeat_ratio": (F.col("n_repeat_words"), F.col("n_words")),
        "symbol_ratio": (F.col("n_symbols"), F.col("n_words")),
        "mean_word_chars": (F.col("word_chars"), F.col("n_words")),
        "stop_ratio": (F.col("n_stop_words"), F.col("n_words")),
        "bang_ratio": (F.col("n_bang_words"), F.col("n_words")),
        "no_letter_ratio": (F.col("n_bare_words"), F.col("n_words")),
        "dup_line_ratio": (F.col("n_dup_lines"), F.col("n_lines")),
    }[name]


def compile_rules(rules: tuple[Rule, ...]) -> Column:
    """True where any rule of the table rejects. Bounds are compared as whole hundredths."""
    failed = F.lit(False)
    for r in rules:
        num, den = _measure(r.measure)
        left, right = num * 100, den * int(round(r.bound * 100))
        hit = left < right if r.op == "<" else left > right
        failed = failed | (hit & (F.col("n_words") >= r.min_words))
    return failed


def apply_quality_rules(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text: str = "text") -> DataFrame:
    """``docs`` with all measures, ``base_failed`` and ``kept``."""
    return (
        measures(docs, text)
        .withColumn("base_failed", compile_rules(BASE))
        .withColumn("kept", ~F.col("base_failed") & ~compile_rules(rules))
    )


OUT = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return apply_quality_rules(docs).select(*OUT)


def kept_documents(docs: DataFrame) -> DataFrame:
    """The documents that pass, with exactly the input's columns."""
    cols = docs.columns
    judged = apply_quality_rules(docs.select(F.struct(*[F.col(f"`{c}`") for c in cols]).alias("_row"), F.col("text")))
    # A random column keeps the filter above the measures; pushed below them, it would
    # inline every measure into every rule.
    held = judged.select("_row", "kept", F.rand(0).alias("_hold"))
    return held.where("kept and _hold >= 0").select("_row.*")


def _sql() -> str:
    stop = ", ".join(f"'{w}'" for w in dict.fromkeys(STOP_WORDS))
    ws = r"[\x20\x09-\x0D]"
    checks = []
    cols = {
        "n_words": ("n_words", "1"),
        "repeat_ratio": ("n_repeat_words", "n_words"),
        "symbol_ratio": ("n_symbols", "n_words"),
        "mean_word_chars": ("word_chars", "n_words"),
        "stop_ratio": ("n_stop", "n_words"),
        "bang_ratio": ("n_bang", "n_words"),
        "no_letter_ratio": ("n_bare", "n_words"),
        "dup_line_ratio": ("n_dup_lines", "n_lines"),
    }
    for r in RULES:
        num, den = cols[r.measure]
        checks.append(f"(n_words >= {r.min_words} AND 100 * {num} {r.op} {int(round(r.bound * 100))} * {den})")
    return f"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS t,
         regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS w
  FROM documents),
word AS (
  SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS i FROM d),
win AS (
  SELECT doc_id, i,
         string_agg(word, ' ') OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 4 FOLLOWING) AS g,
         count(*) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 4 FOLLOWING) AS k
  FROM word),
rep AS (
  SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) > 1 AS twice FROM win WHERE k = 5),
cover AS (
  SELECT doc_id, count(DISTINCT i + j) AS n
  FROM rep, (SELECT unnest([0, 1, 2, 3, 4]) AS j) WHERE twice GROUP BY doc_id),
m AS (
  SELECT d.doc_id, len(w) AS n_words,
         coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
         length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
         len(list_filter(string_split(t, chr(10)), lambda x: length(regexp_replace(x, '{ws}', '', 'g')) > 0)) AS n_lines,
         len(list_distinct(list_filter(string_split(t, chr(10)), lambda x: length(regexp_replace(x, '{ws}', '', 'g')) > 0))) AS n_lines_once,
         coalesce(cover.n, 0)::BIGINT AS n_repeat_words,
         len(list_filter(w, lambda x: lower(x) IN ({stop}))) AS n_stop,
         len(list_filter(w, lambda x: ends_with(x, '!!'))) AS n_bang,
         len(list_filter(w, lambda x: NOT regexp_matches(x, '[\\p{{L}}\\p{{N}}]'))) AS n_bare
  FROM d LEFT JOIN cover USING (doc_id)),
x AS (SELECT *, n_lines - n_lines_once AS n_dup_lines FROM m)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars, n_symbols, n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words,
       (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed,
       NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND NOT ({' OR '.join(checks)}) AS kept
FROM x
"""


SQL = _sql()
