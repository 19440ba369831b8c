"""Wrappers come off at any depth, as a walk over the braces would take them off."""

import random

from pyspark.sql import functions as F

from qacurate.operators import answers as A

NAMES = ("\\boxed", "\\mathrm", "\\mathbf", "\\text", "\\textbf")
#: Values and what is left of them; responses and the inside of their last box.
DEEP = (
    ("\\boxed{\\frac{\\sqrt{2}}{3}}", "\\frac{\\sqrt{2}}{3}"),
    ("\\boxed{\\mathrm{\\mathbf{\\text{\\textbf{7}}}}}", "7"),
    ("\\boxed{x^{2^{n_{k}}} \\mathrm{m}}", "x^{2^{n_{k}}} m"),
    ("\\frac{\\mathrm{a}}{\\mathbf{\\text{b}}}", "\\frac{a}{b}"),
    ("$\\boxed{\\{1, 2\\}}$.", "\\{1, 2\\}"),
    ("\\boxed{5", "\\boxed{5"),
    ("5} and \\text{m", "5} and \\text{m"),
    ("\\boxed{}", ""),
    (None, None),
)
BOXES = (
    ("So \\boxed{\\frac{\\sqrt{2}}{3}} follows, not \\boxed{4", "\\frac{\\sqrt{2}}{3}"),
    ("First \\boxed{1}, then \\boxed{\\mathrm{2}\nm}.", "2\nm"),
    ("\\boxed{a \\boxed{b}}", "a b"),
    ("\\boxed{4 or {\\boxed{5}", "5"),
    ("\\frac{1}{2}", None),
    (None, None),
)


def walked(text):
    stack, gone = [], set()
    for i, c in enumerate(text):
        if c == "{":
            name = next((n for n in NAMES if text[:i].endswith(n)), None)
            stack.append((i, name))
        elif c == "}" and stack:
            at, name = stack.pop()
            if name:
                gone |= {i, *range(at - len(name), at + 1)}
    return "".join(c for i, c in enumerate(text) if i not in gone)


def left(spark, fn, texts):
    rows = spark.createDataFrame(list(enumerate(texts)), "k int, text string").select("k", fn(F.col("text")).alias("value")).collect()
    return [r.value for r in sorted(rows, key=lambda r: r.k)]


def test_deep_wrappers_come_off(spark):
    assert left(spark, A.unwrap, [x for x, _ in DEEP]) == [y for _, y in DEEP]


def test_last_box_at_any_depth(spark):
    assert left(spark, A.extract_boxed_only, [x for x, _ in BOXES]) == [y for _, y in BOXES]


def test_unwrap_is_a_walk_over_the_braces(spark):
    draw = random.Random(5)
    texts = ["".join(draw.choice((*(n + "{" for n in NAMES), "{", "}", "}", "}", "a", "b1", "\\frac{")) for _ in range(draw.randrange(1, 24))) for _ in range(400)]
    assert left(spark, A.unwrap, texts) == [walked(t) for t in texts]


def test_cascade_takes_a_deep_box(spark):
    rows = spark.createDataFrame([("We see.\nThe final answer is \\boxed{\\frac{\\sqrt{2}}{3}}.", "computational"), ("Thus \\boxed{\\mathrm{\\text{\\mathbf{B}}}} holds.", "choice")], "response string, qtype string").withColumn("options", F.lit(None).cast("map<string,string>"))
    assert {(r.rule, r.answer) for r in A.extract_answer(rows).collect()} == {("r1", "\\frac{\\sqrt{2}}{3}"), ("r3", "B")}
