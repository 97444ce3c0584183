"""Quality rules: a table of thresholds compiled into one projection.

Every measure and every verdict is a built-in expression, so the whole operator
is one narrow stage over the scan: no shuffle, no user function.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankflow.llm.common import WS, let, packed, require, unpacked, windows, words

#: Frequent function words of English, French, German and Spanish.
STOP_WORDS = (
    "the of and to in is that it was for on are with as be at this have from or by not an "
    "le la les de des du et un une en est que pour dans qui sur pas au par plus avec ce il "
    "der die das und von zu den mit ist des sich auf nicht ein eine dem im für als auch an "
    "el los las y del que se por con para su al lo como más o pero sus una es no"
).split()
STOP_FORMS = tuple(sorted({form for w in STOP_WORDS for form in (w, w.capitalize())}))


@dataclass(frozen=True)
class Rule:
    """``low <= measure <= high``; a bound of None is open. A null measure passes."""

    name: str
    measure: str
    low: float | None = None
    high: float | None = None


#: The default table. Ratios are per word or per non-blank line.
RULES = (
    Rule("too_few_words", "n_words", low=50),
    Rule("repeated_words", "repeat_word_ratio", high=0.5),
    Rule("word_length", "mean_word_length", low=2.0, high=15.0),
    Rule("symbols", "symbol_ratio", high=0.3),
    Rule("few_letters", "letter_ratio", low=0.55),
    Rule("few_stop_words", "stop_word_ratio", low=0.01),
    Rule("duplicate_lines", "dup_line_ratio", high=0.5),
    Rule("bullets", "bullet_line_ratio", high=0.9),
    Rule("ellipses", "ellipsis_line_ratio", high=0.5),
)


def _repeat_words(w: Column) -> Column:
    """Words inside a three-word window whose text occurs twice or more.

    Window hashes are compared (64 bits); only texts with an equal pair of hashes
    pay for the sort that finds the positions.
    """
    hashes = F.transform(windows(w, 3), lambda x: F.xxhash64(x))

    def spread(starts: Column) -> Column:
        return F.size(F.array_distinct(F.concat(*[_plus(starts, k) for k in range(3)])))

    def by_sorting(h: Column) -> Column:
        placed = F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

        def marks(s: Column) -> Column:
            ahead = F.zip_with(s, F.slice(s, 2, F.size(s)), lambda a, b: F.when(a["h"] == b["h"], F.array(a["i"], b["i"])))
            return spread(F.flatten(F.filter(ahead, lambda x: x.isNotNull())))

        return let(placed, marks)

    def by_lookup(h: Column, twice: Column) -> Column:
        found = F.transform(h, lambda x, i: F.when(F.array_contains(twice, x), i))
        return spread(F.filter(found, lambda x: x.isNotNull()))

    def covered(h: Column) -> Column:
        def same(s: Column) -> Column:
            ahead = F.zip_with(s, F.slice(s, 2, F.size(s)), lambda a, b: F.when(a == b, a))
            return F.filter(F.array_distinct(ahead), lambda x: x.isNotNull())

        twice = let(F.sort_array(h), same)
        return let(twice, lambda d: F.when(F.size(d) == 0, F.lit(0)).when(F.size(d) <= 8, by_lookup(h, d)).otherwise(by_sorting(h)))

    return let(hashes, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(covered(h)))


def _plus(items: Column, k: int) -> Column:
    return F.transform(items, lambda x: x + F.lit(k))


def measured(text: Column) -> Column:
    """A struct of the counts and ratios that rules may name; each is evaluated once per row.

    A null text counts as empty.  Ratios of an empty text are 0.
    """

    def counts(b: Column) -> Column:
        w, lines, joined = b["w"], b["l"], b["j"]
        count = {
            "n_words": F.size(w),
            "word_chars": F.length(joined),
            "n_symbols": F.length(joined) - F.length(F.translate(joined, "#*$%&|<>", "")),
            "n_lines": F.size(lines),
            "n_dup_lines": F.size(lines) - F.size(F.array_distinct(lines)),
            "n_repeat_words": _repeat_words(w),
            "n_letters": F.length(joined) - F.length(F.regexp_replace(joined, r"\p{L}+", "")),
            "n_stop_words": F.size(F.filter(w, lambda x: x.isin(*STOP_FORMS))),
            "n_bullets": F.size(F.filter(lines, lambda x: x.rlike(r"^\s*[-*•‣]"))),
            "n_ellipses": F.size(F.filter(lines, lambda x: x.rlike(r"(?:\.\.\.|…)\s*$"))),
        }
        return F.struct(*[v.cast("long").alias(k) for k, v in count.items()])

    def ratios(c: Column) -> Column:
        each = lambda a, b: F.coalesce(F.try_divide(c[a], c[b]), F.lit(0.0))
        return F.struct(*[c[k].alias(k) for k in COUNTS], *[each(a, b).alias(k) for k, (a, b) in RATIOS.items()])

    text = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: F.length(F.btrim(x, F.lit(WS))) > 0)
    parts = let(words(text), lambda w: F.struct(w.alias("w"), F.array_join(w, "").alias("j"), lines.alias("l")))
    return let(let(parts, counts), ratios)


COUNTS = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words", "n_letters", "n_stop_words", "n_bullets", "n_ellipses")
RATIOS = {
    "mean_word_length": ("word_chars", "n_words"), "symbol_ratio": ("n_symbols", "n_words"), "letter_ratio": ("n_letters", "word_chars"), "stop_word_ratio": ("n_stop_words", "n_words"),
    "dup_line_ratio": ("n_dup_lines", "n_lines"), "repeat_word_ratio": ("n_repeat_words", "n_words"), "bullet_line_ratio": ("n_bullets", "n_lines"), "ellipsis_line_ratio": ("n_ellipses", "n_lines"),
}


def compile_rules(measures: Column, rules: tuple[Rule, ...] = RULES) -> Column:
    """The names of the rules that a struct of :func:`measured` breaks, in table order."""
    broken = []
    for rule in rules:
        value = measures[rule.measure]
        fails = F.lit(False)
        if rule.low is not None:
            fails = fails | (value < rule.low)
        if rule.high is not None:
            fails = fails | (value > rule.high)
        broken.append(F.when(fails, F.lit(rule.name)))
    return F.array_compact(F.array(*broken))


def judged(text: Column, rules: tuple[Rule, ...] = RULES) -> Column:
    """A struct of measures ``m``, ``base_failed``, ``broken_rules`` and ``kept``."""

    def verdict(m: Column) -> Column:
        base = (m["n_words"] < 50) | (100 * m["n_repeat_words"] > 50 * m["n_words"])
        return F.struct(m.alias("m"), base.alias("base_failed"), compile_rules(m, rules).alias("broken_rules"))

    kept = lambda v: F.struct(v["m"].alias("m"), v["base_failed"].alias("base_failed"), v["broken_rules"].alias("broken_rules"), (~v["base_failed"] & (F.size(v["broken_rules"]) == 0)).alias("kept"))
    return let(let(measured(text), verdict), kept)


def quality_report(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text") -> DataFrame:
    """``docs`` with measures, ``base_failed``, ``broken_rules`` and ``kept``.

    Empty tables give an empty result; repeated rows are judged alike; columns of
    the input that carry one of these names are replaced.
    """
    require(docs, [text_col])
    out = packed(docs).withColumn("j", judged(F.col(f"row.{text_col}"), rules))
    made = {k: F.col(f"j.m.{k}") for k in (*COUNTS, *RATIOS)} | {k: F.col(f"j.{k}") for k in ("base_failed", "broken_rules", "kept")}
    return unpacked(out, docs.columns, made)


def keep_quality(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that pass, with its columns; the verdict is one expression in the filter."""
    require(docs, [text_col])
    return docs.where(judged(F.col(text_col), rules)["kept"])
