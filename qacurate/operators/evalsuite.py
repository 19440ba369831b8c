"""The evaluation suite: registry of benchmarks, prompts, rendered items and responses."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from qacurate.operators.answers import extract_answer, grade

#: Slot, benchmark, category, subject, question type, whether a unit is asked, whether it counts in averages.
REGISTRY = (
    (0, "MMLU", "General", "General", "choice", False, False),
    (1, "GPQA-Diamond", "General", "General", "choice", False, True),
    (2, "MMLU-Pro", "General", "General", "choice", False, True),
    (3, "SuperGPQA", "General", "General", "choice", False, True),
    (4, "SciBench", "General", "General", "computational", True, True),
    (5, "OlympicArena", "General", "General", "computational", True, True),
    (6, "ChemBench", "Specific", "Chemistry", "mixed", False, True),
    (7, "CS-Bench", "Specific", "Computer science", "truefalse", False, True),
    (8, "MedQA", "Specific", "Medicine", "choice", False, True),
    (9, "MedMCQA", "Specific", "Medicine", "choice", False, True),
    (10, "PubMedQA", "Specific", "Medicine", "choice", False, True),
    (11, "PIQA", "Specific", "Physics", "choice", False, True),
    (12, "GSM8K", "Math", "Math", "computational", False, True),
    (13, "MATH", "Math", "Math", "computational", False, True),
    (14, "MATH500", "Math", "Math", "computational", False, True),
)
COLUMNS = "slot int, benchmark string, category string, subject string, kind string, needs_unit boolean, in_average boolean"
MODELS = 6


def registry(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(REGISTRY), COLUMNS).withColumn("metric", F.when(F.col("needs_unit"), "EM (unit)").otherwise("EM"))


@dataclass(frozen=True)
class EvalTask:
    """How a benchmark is asked. style: chat or base. shots: worked examples before the question."""

    benchmark: str
    style: str = "chat"
    shots: int = 0
    reasoning: bool = True


def render_prompt(question: Column, task: EvalTask, example: str = "Q: What is 1 + 1?\nA: The final answer is 2.") -> Column:
    lead = "Reason step by step, then give the final answer.\n" if task.reasoning else ""
    shots = (example + "\n\n") * task.shots
    if task.style == "chat":
        return F.concat(F.lit(f"user: {lead}{shots}"), question)
    return F.concat(F.lit(f"{shots}{lead}Q: "), question, F.lit("\nA:"))


def items(part: DataFrame, reg: DataFrame) -> DataFrame:
    """Items rendered on rows of ``part``: the benchmark by key, the gold from price, size or brand."""
    met = part.withColumn("slot", (F.col("p_partkey") % len(REGISTRY)).cast("int")).join(F.broadcast(reg), "slot")
    even = F.col("p_partkey") % 2 == 0
    qtype = F.when(F.col("kind") == "mixed", F.when(even, "choice").otherwise("computational")).otherwise(F.col("kind"))
    label = F.substring(F.lit("ABCD"), (F.col("p_partkey") % 4 + 1).cast("int"), 1)
    options = F.map_from_arrays(F.array(*[F.lit(x) for x in "ABCD"]), F.transform(F.sequence(F.lit(0), F.lit(3)), lambda i: F.concat(F.lit("brand-"), F.col("p_brand"), F.lit("-"), ((F.col("p_partkey") + i) % 97).cast("string"), F.lit("x"))))
    gold = F.when(qtype == "choice", label).when(qtype == "truefalse", F.when(even, "true").otherwise("false")).otherwise(F.col("p_size").cast("string"))
    return met.select("benchmark", "category", "in_average", F.col("p_partkey").alias("item_id"), qtype.alias("qtype"), "needs_unit", gold.alias("gold"), F.when(F.col("needs_unit"), "m").alias("gold_unit"), F.when(qtype == "choice", options).alias("options"))


def responses(items_: DataFrame, models: int = MODELS) -> DataFrame:
    """Planted responses of ``models`` systems: right for a known share, in one of eight forms.

    System k is right where (item + 7 k) mod 10 < 3 + k. Form 7 says nothing; form 6 gives a wrong unit.
    """
    grid = items_.withColumn("model_no", F.explode(F.sequence(F.lit(0), F.lit(models - 1))))
    right = (F.col("item_id") + 7 * F.col("model_no")) % 10 < 3 + F.col("model_no")
    form = ((F.col("item_id") + F.col("model_no")) % 8).cast("int")
    wrong = F.when(F.col("qtype") == "choice", F.when(F.col("gold") == "A", "B").otherwise("A")).when(F.col("qtype") == "truefalse", F.when(F.col("gold") == "true", "false").otherwise("true")).otherwise((F.col("gold").cast("int") + 1000).cast("string"))
    value = F.when(right, F.col("gold")).otherwise(wrong)
    unit = F.when(F.col("needs_unit"), F.lit(" m")).otherwise(F.lit(""))
    full = F.concat(value, unit)
    content = F.element_at("options", value)
    texts = [
        F.concat(F.lit("We compute. The final answer is \\boxed{"), full, F.lit("}.")),
        F.concat(F.lit("So \\boxed{\\mathrm{"), full, F.lit("}} follows.")),
        F.concat(F.lit("Work it out.\nThe correct answer is **"), full, F.lit("**")),
        F.concat(F.lit("Some steps.\nThe final answer is "), full, F.lit(".")),
        F.concat(F.lit("Some steps.\nAnswer: "), full),
        F.when(F.col("qtype") == "choice", F.concat(F.lit("I would pick "), content, F.lit(" here."))).otherwise(F.concat(F.lit("It comes out as "), full)),
        F.when(F.col("needs_unit"), F.concat(F.lit("The final answer is "), value, F.lit(" kg."))).otherwise(F.concat(F.lit("The final answer is "), full, F.lit("."))),
        F.lit("I do not know."),
    ]
    said = F.get(F.array(*texts), form)
    planted = right & (form != 7) & ~((form == 6) & F.col("needs_unit"))
    return grid.withColumn("model", F.concat(F.lit("system_"), F.col("model_no").cast("string"))).withColumn("template", form).withColumn("response", said).withColumn("planted", planted)


def evaluate(items_: DataFrame, models: int = MODELS) -> DataFrame:
    """Instance-level output of all systems on all items: response, answer, rule, correct."""
    return grade(extract_answer(responses(items_, models)))
