"""Answer extraction and grading: a cascade of rules, unwrapping, option matching, numbers with units."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from qacurate.functions.text import let

INDICATOR = "(?i)(?:the final answer to this question is|the final answer is|the correct answer is|the answer is|answer:)\\s*"
WRAPPER = "\\\\(?:boxed|mathrm|mathbf|text|textbf)\\{$"
BOXED = "\\\\boxed\\{$"
NUMBER = "(-?[0-9][0-9,]*\\.?[0-9]*(?:[eE][-+]?[0-9]+)?(?:/[0-9]+)?)"
UNIT = "([A-Za-z%][A-Za-z0-9/^%]*)?"
#: Spellings of units.
UNIT_ALIASES = (("meters", "m"), ("meter", "m"), ("metres", "m"), ("metre", "m"), ("seconds", "s"), ("second", "s"), ("kilograms", "kg"), ("kilogram", "kg"), ("dollars", "usd"), ("usd", "usd"), ("percent", "%"))
RULES = ("r1", "r2", "r3", "r4", "r5", "r6", "r7", "r8", "r9")


def _last(text: Column, pattern: str) -> Column:
    """The first group of a pattern's last match; null if there is none."""
    found = F.regexp_extract_all(text, F.lit(pattern), 1)
    return F.when(F.size(found) > 0, F.element_at(found, -1))


def find_indicator(text: Column) -> Column:
    """What follows the last indicator phrase, up to the end of its line; null without one."""
    return _last(text, f"{INDICATOR}([^\\n]+)")


def _pieces(text: Column) -> Column:
    """A text cut behind each of its braces; those behind a backslash are no braces."""
    return F.split(text, "(?<=(?<!\\\\)[{}])")


def _matched(pieces: Column, opener: str) -> Column:
    """(start, end) of the pieces that open and close a group, in order of their ends, at any depth; openers match a pattern."""
    none = F.array().cast("array<struct<start: int, end: int>>")
    start = F.struct(F.lit(0).alias("i"), F.array().cast("array<int>").alias("open"), none.alias("found"))

    def step(s: Column, x: Column) -> Column:
        i, opens, closes = s["i"], F.endswith(x, F.lit("{")) & ~F.endswith(x, F.lit("\\{")), F.endswith(x, F.lit("}")) & ~F.endswith(x, F.lit("\\}"))
        some = closes & (F.size(s["open"]) > 0)
        top = F.get(s["open"], F.size(s["open"]) - 1)  # below 0: a brace that no opener has
        stack = F.when(opens, F.array_append(s["open"], F.when(x.rlike(opener), i).otherwise(-1))).when(some, F.slice(s["open"], 1, F.size(s["open"]) - 1)).otherwise(s["open"])
        found = F.when(some & (top >= 0), F.array_append(s["found"], F.struct(top.alias("start"), i.alias("end")))).otherwise(s["found"])
        return F.struct((i + 1).alias("i"), stack.alias("open"), found.alias("found"))

    return F.aggregate(pieces, start, step, lambda s: s["found"])


def _opened(text: Column) -> Column:
    """Without wrappers whose braces match; all else stays."""

    def rest(pieces: Column, found: Column) -> Column:
        ends = lambda x, i: F.when(F.array_contains(found["end"], i), F.substr(x, F.lit(1), F.length(x) - 1)).otherwise(x)
        return F.array_join(F.transform(pieces, lambda x, i: F.when(F.array_contains(found["start"], i), F.regexp_replace(x, WRAPPER, "")).otherwise(ends(x, i))), "")

    return F.when(text.rlike(WRAPPER[:-1]), let(_pieces(text), lambda p: let(_matched(p, WRAPPER), lambda found: rest(p, found)))).otherwise(text)


def last_boxed(text: Column) -> Column:
    """The inside of the last boxed group, the outermost of nested ones; null if there is none."""

    def inside(pieces: Column, last: Column) -> Column:
        return let(F.array_join(F.slice(pieces, last["start"] + 2, last["end"] - last["start"]), ""), lambda x: F.substr(x, F.lit(1), F.length(x) - 1))

    return F.when(text.contains("\\boxed{"), let(_pieces(text), lambda p: let(F.try_element_at(_matched(p, BOXED), F.lit(-1)), lambda last: F.when(last.isNotNull(), inside(p, last)))))


def unwrap(value: Column) -> Column:
    """The inside of wrappers, however deep: boxed, text styles, bold, dollars, one pair of brackets; ends trimmed."""
    value = F.regexp_replace(_opened(value), "\\\\left|\\\\right|\\\\,|\\\\;|\\\\ |\\$|\\*\\*", "")
    value = F.regexp_replace(F.trim(value), "^\\(([^()]*)\\)$", "$1")
    return F.trim(F.regexp_replace(F.trim(value), "[.\\s]+$", ""))


def extract_boxed_only(text: Column) -> Column:
    return unwrap(last_boxed(text))


def match_option(text: Column, options: Column) -> Column:
    """The label of the one option whose content occurs in the text; null if none or several do."""
    low = F.lower(text)
    hits = F.filter(F.map_entries(options), lambda e: F.contains(low, F.lower(e["value"])))
    return F.when(F.size(hits) == 1, F.get(hits, 0)["key"])


def split_unit(value: Column) -> Column:
    """(number, unit) of a value: the number's normal form and the unit's."""
    number = F.regexp_extract(value, NUMBER, 1)
    unit = F.lower(F.regexp_extract(value, f"{NUMBER}\\s*{UNIT}", 2))
    return F.struct(norm_number(number).alias("number"), norm_unit(unit).alias("unit"))


def norm_number(text: Column) -> Column:
    """A decimal of six places: thousands separators dropped, fractions and powers of ten worked out."""
    plain = F.replace(text, F.lit(","), F.lit(""))
    over = F.split_part(plain, F.lit("/"), F.lit(2))
    top = F.split_part(plain, F.lit("/"), F.lit(1)).try_cast("double")
    value = F.when(over != "", F.try_divide(top, over.try_cast("double"))).otherwise(top)
    return F.round(value, 6)


def norm_unit(unit: Column) -> Column:
    table = F.create_map(*[F.lit(x) for pair in UNIT_ALIASES for x in pair])
    return F.nullif(F.coalesce(table[unit], unit), F.lit(""))


def _rules(text: Column, qtype: Column, options: Column) -> list[tuple[str, Column]]:
    said = find_indicator(text)
    last_line = F.substring_index(F.rtrim(text), "\n", -1)
    choice, number = qtype == "choice", qtype == "computational"
    label = F.when(choice, F.upper(F.regexp_extract(unwrap(said), "^([A-Ja-j])(?:[).:]|$| )", 1))).otherwise(unwrap(said))
    return [
        ("r1", F.when(said.contains("\\boxed{"), unwrap(last_boxed(said)))),
        ("r2", F.nullif(label, F.lit(""))),
        ("r3", unwrap(last_boxed(text))),
        ("r4", F.when(number, unwrap(F.nullif(F.regexp_extract(last_line, "(\\*\\*[^*]+\\*\\*|\\$[^$]+\\$)[. ]*$", 1), F.lit(""))))),
        ("r5", F.when(choice, F.upper(F.nullif(F.regexp_extract(last_line, "(?:^|[ (])([A-Ja-j])(?:[).]|$)", 1), F.lit(""))))),
        ("r6", F.when(choice, match_option(text, options))),
        ("r7", F.when(qtype == "truefalse", F.when(F.lower(last_line).rlike("not true|false|incorrect"), "false").when(F.lower(last_line).rlike("true|correct"), "true"))),
        ("r8", F.when(number, F.nullif(F.trim(_last(last_line, "(-?[0-9][0-9,]*\\.?[0-9]*(?:/[0-9]+)? ?[A-Za-z%]*)")), F.lit("")))),
    ]


def _named(rule: str, value: Column) -> Column:
    """(rule, answer) if the value says something, else null."""
    return let(value.cast("string"), lambda x: F.when(x != "", F.struct(F.lit(rule).alias("rule"), x.alias("answer"))))


def extract_answer(df: DataFrame, text: str = "response", qtype: str = "qtype", options: str = "options") -> DataFrame:
    """Adds ``answer`` and ``rule``: the first rule that yields a value, and its id; r9 where none does."""
    rules = _rules(F.coalesce(F.col(text), F.lit("")), F.col(qtype), F.col(options))
    # Later rules are worked out only where the earlier ones gave nothing.
    tried = [_named(r, v) for r, v in rules]
    out = df.withColumn("_first", F.coalesce(*tried))
    return out.withColumn("rule", F.coalesce(F.col("_first.rule"), F.lit("r9"))).withColumn("answer", F.col("_first.answer")).drop("_first")


def normal(value: Column) -> Column:
    return F.lower(F.trim(F.regexp_replace(value, "[ \\t\\n]+", " ")))


def exact_match(answer: Column, gold: Column, qtype: Column) -> Column:
    """Equal normal forms; numbers compare as numbers."""
    a, g = split_unit(answer), split_unit(gold)
    same = F.when(qtype == "computational", a["number"] == g["number"]).otherwise(normal(answer) == normal(gold))
    return F.coalesce(same, F.lit(False))


def exact_match_unit(answer: Column, gold: Column, gold_unit: Column) -> Column:
    """Number and unit must both match; a missing unit is wrong."""
    a = split_unit(answer)
    return F.coalesce((a["number"] == split_unit(gold)["number"]) & (a["unit"] == norm_unit(F.lower(gold_unit))), F.lit(False))


def grade(df: DataFrame) -> DataFrame:
    """Adds ``correct`` by the item's type and whether its unit counts."""
    em, unit = exact_match(F.col("answer"), F.col("gold"), F.col("qtype")), exact_match_unit(F.col("answer"), F.col("gold"), F.col("gold_unit"))
    return df.withColumn("correct", F.when(F.col("needs_unit"), unit).otherwise(em))


def extraction_report(graded: DataFrame) -> DataFrame:
    """(rule, n, n_correct, n_boxed): what each rule gives, and what a boxed-only extractor would have given."""
    boxed = extract_boxed_only(F.col("response")).isNotNull()
    return graded.groupBy("rule").agg(F.count(F.lit(1)).alias("n"), F.count_if("correct").alias("n_correct"), F.count_if(boxed).alias("n_boxed"))
