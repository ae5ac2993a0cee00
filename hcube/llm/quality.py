"""Quality rules: a threshold table compiled into one Spark projection.

Every figure comes from built-in functions over the whole text of a row, so the
plan is a scan and a few projections: no shuffle, no Python.  A null text counts
as empty; empty texts fail the base rule; extra columns are left alone by
``annotate`` and not read by ``op8_quality_rules``.  Rows are judged one by one,
so repeated rows and ties need no rule; very long texts are judged whole, in one row;
an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# White space that ends a word, and the symbols that are counted.
WHITE = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
# Frequent function words of the four languages of the tables.
STOP_WORDS = (
    "the of and to in is that for it with on as by this be are from or at an was "
    "le la les de des et un une que est pour dans qui sur pas du au par avec "
    "der die das und ist nicht von zu den mit ein eine sich auf im dem es auch "
    "el los las en y por con para del se al lo como su no"
).split()

MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50


@dataclass(frozen=True)
class Rule:
    """Passes while ``low <= numerator / denominator <= high`` (a side may be open)."""

    name: str
    numerator: str
    denominator: str | None = None
    low: float | None = None
    high: float | None = None

    def holds(self) -> Column:
        """The comparison without a division, so a zero denominator needs no case."""
        base = F.col(self.denominator).cast("double") if self.denominator else F.lit(1.0)
        value = F.col(self.numerator).cast("double")
        out = F.lit(True)
        if self.low is not None:
            out = out & (value >= base * F.lit(self.low))
        if self.high is not None:
            out = out & (value <= base * F.lit(self.high))
        return out


DEFAULT_RULES = (
    Rule("word_length", "word_chars", "n_words", 2.0, 14.0),
    Rule("symbols", "n_symbols", "n_words", None, 0.1),
    Rule("exclamations", "n_exclaims", "n_words", None, 0.5),
    Rule("stop_words", "n_stop_words", "n_words", 0.05, None),
    Rule("dup_lines", "n_dup_lines", "n_lines", None, 0.5),
    Rule("ellipsis_lines", "n_ellipsis_lines", "n_lines", None, 0.3),
    Rule("bullet_lines", "n_bullet_lines", "n_lines", None, 0.9),
)

MEASURES = (
    "n_words", "word_chars", "n_symbols", "n_exclaims", "n_stop_words", "n_lines",
    "n_dup_lines", "n_ellipsis_lines", "n_bullet_lines", "n_repeat_words",
)


def annotate(docs: DataFrame, text: str = "text", prefix: str = "") -> DataFrame:
    """Adds the measures of ``MEASURES`` (long) to every row, each name behind ``prefix``.

    The windows of three words are compared by a 64-bit hash: sorted with their
    place in the low bits, equal neighbours are windows found twice.  All steps are
    array functions of the row, so a row of any length stays in its task.
    """
    tag = "__q_"
    own = docs.columns
    blank = " " * (len(WHITE) - 1)
    step = docs.withColumn(f"{tag}t", F.coalesce(F.col(text), F.lit("")))
    # Each select fixes arrays that the next one refers to inside lambdas.
    step = step.withColumns(
        {
            f"{tag}words": F.expr(
                f"array_remove(split(translate({tag}t, '{_sql(WHITE[1:])}', '{blank}'), ' '), '')"
            ),
            f"{tag}lines": F.expr(
                f"filter(split({tag}t, '\\n'), x -> length(translate(x, '{_sql(WHITE)}', '')) > 0)"
            ),
        }
    )
    step = step.withColumns(
        {
            f"{tag}n": F.expr(f"size({tag}words)"),
            f"{tag}bits": F.expr(f"length(bin(cast(size({tag}words) as bigint)))"),
            f"{tag}h": F.expr(
                f"transform(slice({tag}words, 1, greatest(size({tag}words) - 2, 0)), "
                f"(x, i) -> xxhash64(x, get({tag}words, i + 1), get({tag}words, i + 2)))"
            ),
        }
    )
    step = step.withColumn(
        f"{tag}s",
        F.expr(
            f"CASE WHEN size(array_distinct({tag}h)) < size({tag}h) THEN "
            f"sort_array(transform({tag}h, (x, i) -> shiftleft(x, {tag}bits) | cast(i as bigint))) "
            f"ELSE cast(array() as array<bigint>) END"
        ),
    )
    place = f"cast({{}} & (shiftleft(1L, {tag}bits) - 1) as int)"
    near = (
        f"(shiftrightunsigned(x, {tag}bits) = shiftrightunsigned(get({tag}s, i {{0}} 1), {tag}bits) AND "
        f"get({tag}h, {place.format('x')}) = get({tag}h, {place.format(f'get({tag}s, i {{0}} 1)')}))"
    )
    step = step.withColumn(
        f"{tag}d",
        F.expr(
            f"sort_array(transform(filter({tag}s, (x, i) -> coalesce({near.format('+')}, false) "
            f"OR (i > 0 AND {near.format('-')})), x -> {place.format('x')}))"
        ),
    )
    out = {
        "n_words": F.col(f"{tag}n").cast("long"),
        "word_chars": F.expr(f"length(translate({tag}t, '{_sql(WHITE)}', ''))").cast("long"),
        "n_symbols": F.expr(f"length({tag}t) - length(translate({tag}t, '{_sql(SYMBOLS)}', ''))").cast("long"),
        "n_exclaims": F.expr(f"length({tag}t) - length(translate({tag}t, '!', ''))").cast("long"),
        "n_stop_words": F.size(F.filter(F.col(f"{tag}words"), lambda x: x.isin(*STOP_WORDS))).cast("long"),
        "n_lines": F.size(f"{tag}lines").cast("long"),
        "n_dup_lines": F.expr(f"size({tag}lines) - size(array_distinct({tag}lines))").cast("long"),
        "n_ellipsis_lines": F.expr(f"size(filter({tag}lines, x -> rtrim(x) LIKE '%...'))").cast("long"),
        "n_bullet_lines": F.expr(
            f"size(filter({tag}lines, x -> left(ltrim(x), 1) IN ('-', '*', '•')))"
        ).cast("long"),
        "n_repeat_words": F.expr(
            f"aggregate(transform({tag}d, (x, i) -> CASE WHEN i = 0 THEN 3 ELSE least(3, x - get({tag}d, i - 1)) END), "
            f"0L, (a, x) -> a + x) + CASE WHEN monotonically_increasing_id() < 0 THEN 1L ELSE 0L END"
        ),
    }
    # The row number above adds nothing.  It keeps filters on these columns from being pushed
    # below this projection, where the nested arrays would be written out once per use.
    return step.select(*[F.col(f"`{c}`") for c in own], *[c.alias(prefix + k) for k, c in out.items()])


def _sql(chars: str) -> str:
    """Characters inside a SQL literal, white space and quotes by escapes."""
    return "".join(c if c.isprintable() and c not in "'\\" else f"\\u{ord(c):04X}" for c in chars)


def verdicts(rules=DEFAULT_RULES) -> tuple[Column, Column, Column]:
    """``base_failed``, ``failed_rules`` (names of the table's rules), ``kept`` over ``annotate``'s columns."""
    base = (F.col("n_words") < MIN_WORDS) | (
        100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words")
    )
    failed = F.filter(
        F.array(*[F.when(~r.holds(), F.lit(r.name)) for r in rules]), lambda x: x.isNotNull()
    )
    kept = ~base
    for r in rules:
        kept = kept & r.holds()
    return base, failed, kept


def op8_quality_rules(docs: DataFrame, rules=DEFAULT_RULES) -> DataFrame:
    """One row per document: the measures, ``base_failed``, ``kept`` and ``failed_rules``."""
    base, failed, kept = verdicts(rules)
    return annotate(docs.select("doc_id", "text")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        base.alias("base_failed"), kept.alias("kept"),
        F.array_join(failed, ",").alias("failed_rules"),
    )


def keep_good(docs: DataFrame, rules=DEFAULT_RULES) -> DataFrame:
    """The rows of ``docs`` that pass every rule, with their own columns only."""
    prefix = "__m_"
    marked = annotate(docs, prefix=prefix)
    renamed = tuple(
        Rule(r.name, prefix + r.numerator, r.denominator and prefix + r.denominator, r.low, r.high) for r in rules
    )
    ok = (F.col(f"{prefix}n_words") >= MIN_WORDS) & (
        100 * F.col(f"{prefix}n_repeat_words") <= MAX_REPEAT_PERCENT * F.col(f"{prefix}n_words")
    )
    for r in renamed:
        ok = ok & r.holds()
    return marked.filter(ok).select(*[F.col(f"`{c}`") for c in docs.columns])
