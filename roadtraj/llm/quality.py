"""Quality rules: a threshold table compiled into one Spark projection.

Measures (lengths, symbols, repeated lines and word windows, stop words) are
built-in array and string expressions; the rules are rows of ``RULES`` and
become one boolean column. No user function runs.

Defined results: a null or blank text has no words and fails; every input row
gives one output row, repeated rows included; extra columns are ignored by
``measure`` and kept by ``keep``; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD_GAP = r"[\x20\x09-\x0D]+"
_BLANKS = " \t\n\x0b\x0c\r"

# Frequent function words of English, German, French and Spanish.
STOP_WORDS = (
    "the of and to in a is that it for on was be with as by this at are an from or have not "
    "der die und den von zu das mit sich des auf ist im dem ein eine für er es sie nicht "
    "de la le et les un une des du en est que qui dans pour au il elle pas sur "
    "el los las y del se por con una su para como más lo al"
).split()

# Measure, least, most (null: open) of a kept document.
RULES: tuple[tuple[str, float | None, float | None], ...] = (
    ("n_words", 50, None),
    ("repeat_percent", None, 50),
    ("mean_word_chars", 2, 14),
    ("symbol_ratio", None, 0.1),
    ("dup_line_ratio", None, 0.5),
    ("n_stop_kinds", 2, None),
)
_BASE_RULES = ("n_words", "repeat_percent")


def compile_rules(rules=RULES) -> Column:
    """One boolean column: every measure lies within its bounds."""
    passed = F.lit(True)
    for measure, least, most in rules:
        for bound, inside in ((least, F.col(measure) >= F.lit(least)), (most, F.col(measure) <= F.lit(most))):
            if bound is not None:
                passed = passed & inside
    return passed


def _array(name: str, empty: str) -> Column:
    return F.coalesce(F.col(name), F.expr(empty))


def measure(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns and every measure of each document's whole text.

    A window is three consecutive words; ``n_repeat_words`` counts the words
    inside windows that occur at least twice in the text. Windows are compared
    by a 64-bit hash, sorted once per text, so the cost is n log n.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    words = docs.select(*[F.col(c) for c in keep], text.alias("_t"), F.btrim(text, F.lit(_BLANKS)).alias("_b")).select(
        *keep,
        F.when(F.col("_b") == "", F.expr("cast(array() as array<string>)")).otherwise(F.split("_b", WORD_GAP)).alias("_w"),
        F.length(F.regexp_replace("_t", r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        F.expr(r"filter(split(_t, '\n'), x -> x rlike '[^\\x20\\x09-\\x0D]')").alias("_l"),
    )
    counted = words.select(
        *keep,
        "n_symbols",
        F.size("_w").cast("long").alias("n_words"),
        F.length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        F.size("_l").cast("long").alias("n_lines"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        F.size(F.array_intersect("_w", F.array(*[F.lit(w) for w in dict.fromkeys(STOP_WORDS)]))).cast("long").alias("n_stop_kinds"),
        F.expr("CASE WHEN size(_w) >= 3 THEN transform(sequence(0, size(_w) - 3), i -> xxhash64(_w[i], _w[i + 1], _w[i + 2])) ELSE cast(array() as array<bigint>) END").alias("_h"),
    )
    names = [c for c in counted.columns if c != "_h"]
    ordered = counted.select(
        *names,
        F.expr(
            "CASE WHEN size(array_distinct(_h)) < size(_h) THEN sort_array(transform(_h, (h, i) -> struct(h, i))) "
            "ELSE cast(array() as array<struct<h: bigint, i: int>>) END"
        ).alias("_s"),
    )
    repeated = ordered.select(
        *names,
        F.expr("sort_array(array_compact(transform(_s, (x, k) -> CASE WHEN x.h = try_element_at(_s, k + 2).h OR (k > 0 AND x.h = try_element_at(_s, greatest(k, 1)).h) THEN x.i END)))").alias("_i"),
    )
    measured = repeated.withColumn(
        "n_repeat_words",
        F.expr("aggregate(_i, named_struct('t', 0L, 'last', -3), (a, x) -> named_struct('t', a.t + least(3, x - a.last), 'last', x), a -> a.t)"),
    ).drop("_i")
    some = F.greatest(F.col("n_words"), F.lit(1))
    return measured.withColumns(
        {
            "repeat_percent": 100.0 * F.col("n_repeat_words") / some,
            "mean_word_chars": F.col("word_chars") / some,
            "symbol_ratio": F.col("n_symbols") / some,
            "dup_line_ratio": F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1)),
        }
    )


def verdicts(docs: DataFrame) -> DataFrame:
    """Measures of each document, ``base_failed`` and ``kept``."""
    base = compile_rules(tuple(r for r in RULES if r[0] in _BASE_RULES))
    return measure(docs).withColumns({"base_failed": ~base, "kept": compile_rules()})


def keep(docs: DataFrame) -> DataFrame:
    """The documents that pass every rule, with the columns they came with."""
    names = [c for c in docs.columns]
    held = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("_row"), F.col("text"))
    # The fence keeps the filter above the measures; pushed below, it would evaluate them anew for each word.
    fenced = measure(held, keep=("_row",)).withColumn("_fence", F.monotonically_increasing_id())
    return fenced.where(compile_rules() & (F.col("_fence") >= 0)).select("_row.*")
