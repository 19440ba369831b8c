"""Clients that answer prompts, and a call that asks only what it has not asked before.

A client maps a batch of prompts to a batch of answers. The operators that play a model's part take a
``Model`` (a client and the table of its answers); without one they use rules, which are column
expressions and need no client.
"""

from __future__ import annotations

import json
import re
import time
import urllib.request
from collections.abc import Iterator
from dataclasses import dataclass, field
from typing import Protocol

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from qacurate.staging import Staged


class ModelClient(Protocol):
    version: str

    def complete(self, prompts: list[str]) -> list[str]: ...


@dataclass(frozen=True)
class EchoClient:
    """Answers with a fixed text and the prompt's length; for tests."""

    version: str = "echo-1"

    def complete(self, prompts: list[str]) -> list[str]:
        return [f"echo {len(p)}" for p in prompts]


@dataclass(frozen=True)
class HttpClient:
    """Posts {"prompts": [...]} and reads {"answers": [...]}; retries with growing pauses."""

    url: str
    version: str
    timeout: float = 60.0
    tries: int = 4
    per_second: float = 0.0
    headers: dict[str, str] = field(default_factory=dict)

    def complete(self, prompts: list[str]) -> list[str]:
        body = json.dumps({"prompts": prompts}).encode()
        for attempt in range(self.tries):
            try:
                request = urllib.request.Request(self.url, body, {"Content-Type": "application/json", **self.headers})
                with urllib.request.urlopen(request, timeout=self.timeout) as reply:
                    answers = json.load(reply)["answers"]
                if len(answers) != len(prompts):
                    raise ValueError(f"{len(answers)} answers to {len(prompts)} prompts")
                if self.per_second:
                    time.sleep(len(prompts) / self.per_second)
                return answers
            except (OSError, ValueError, KeyError):
                if attempt + 1 == self.tries:
                    raise
                time.sleep(2**attempt)
        return []


@dataclass(frozen=True)
class TableClient:
    """Answers from given pairs of prompt and answer, with ``other`` for any other prompt; for tests."""

    answers: tuple[tuple[str, str], ...]
    other: str = ""
    version: str = "table-1"

    def complete(self, prompts: list[str]) -> list[str]:
        known = dict(self.answers)
        return [known.get(p, self.other) for p in prompts]


@dataclass(frozen=True)
class ReplayClient:
    """Marks a call that may only be answered from the cache."""

    version: str

    def complete(self, prompts: list[str]) -> list[str]:
        raise LookupError(f"{len(prompts)} prompts have no stored answer")


#: Prompts of the roles; ours, as the reference prints none.
PROMPTS = {
    "classify": "Name the subjects and the academic level of this text as JSON with the keys subjects and level.\n\n{text}",
    "extract_high": "List as a JSON list of objects with the keys question and answer the questions of this text that need several reasoning steps and whose full solution it holds.\n\n{text}",
    "extract_low": "List as a JSON list of objects with the keys question and answer all complete questions with answers in this text.\n\n{text}",
    "refine": "Given the source, make the question self-contained and the answer complete. Reply as JSON with the keys question and answer.\n\nSource: {chunk}\nQuestion: {question}\nAnswer: {answer}",
    "gap": "Does the answer lack a reasoning process? Answer yes or no.\n\nQuestion: {question}\nAnswer: {answer}",
    "explain": "Add the missing explanation and end with the final answer.\n\nQuestion: {question}\nAnswer: {answer}",
    "defects": "Name as a JSON list the defects: external reference, contradiction, missing information, invalid.\n\nQuestion: {question}\nAnswer: {answer}",
    "paraphrase": "Are these two questions paraphrases? Answer yes or no.\n\n1: {question}\n2: {item}",
    "score": "Score the response from 0 to 10 against the reference.\n\nReference: {reference}\nResponse: {response}",
    "sample": "Answer the question (attempt {k}).\n\nQuestion: {question}",
    "annotate": "Solve the question step by step and end with the final answer.\n\nQuestion: {question}\nReference: {answer}",
    "digitise": "Transcribe this page as plain text.\n\n{page}",
    "synthesise": "Write one question that this text answers.\n\n{text}",
}
CACHE = "key string, role string, n_prompt long, answer string"


def prompt(role: str, **columns: str) -> F.Column:
    """A role's prompt with its fields taken from columns."""
    parts = re.split(r"\{(\w+)\}", PROMPTS[role])
    out = [F.lit(p) if i % 2 == 0 else F.coalesce(F.col(columns.get(p, p)).cast("string"), F.lit("")) for i, p in enumerate(parts)]
    return F.concat(*out)


def call_model(df: DataFrame, role: str, text: F.Column, client: ModelClient, cache: str, output: str = "answer", batch: int = 64) -> DataFrame:
    """Adds ``output``: the client's answer to each prompt.

    cache: path of a Parquet table of answers by prompt key, which only grows. Distinct prompts without
    an answer are asked once, and their answers are committed before anything reads them, so that a lost
    executor never repeats a paid call that was kept.
    """
    spark = df.sparkSession
    version = client.version
    keyed = Staged(df.withColumn("_prompt", text).withColumn("_key", F.sha2(F.concat_ws("\x1f", F.lit(role), F.lit(version), "_prompt"), 256)), "prompts").df
    spark.createDataFrame([], CACHE).write.mode("append").parquet(cache)
    known = spark.read.schema(CACHE).parquet(cache)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, batch):
                part = b.slice(at, batch)
                prompts = part.column("prompt").to_pylist()
                sizes = pa.array([len(p.split()) for p in prompts], pa.int64())
                yield pa.RecordBatch.from_arrays([part.column("key"), pa.array([role] * len(prompts)), sizes, pa.array(client.complete(prompts), pa.string())], names=["key", "role", "n_prompt", "answer"])

    asked = keyed.select(F.col("_key").alias("key"), F.col("_prompt").alias("prompt")).dropDuplicates(["key"]).join(known, "key", "left_anti")
    asked.mapInArrow(ask, CACHE).write.mode("append").parquet(cache)
    answers = spark.read.schema(CACHE).parquet(cache).groupBy(F.col("key").alias("_key")).agg(F.min("answer").alias(output))
    # Written at once: Spark takes two reads of one path for equal, though the table has grown between them, and a
    # plan that holds the answers of two calls would use those of the first for both.
    return Staged(keyed.join(answers, "_key", "left").drop("_key", "_prompt"), "answered").df


def parsed(answer: F.Column, schema: str) -> F.Column:
    """A model's JSON; what does not parse is null, never an error."""
    return F.from_json(answer, schema, {"mode": "PERMISSIVE"})


def usage(spark: SparkSession, cache: str) -> DataFrame:
    """(role, calls, prompt_words, answer_words): what was asked for and paid, from the stored answers."""
    calls = spark.read.schema(CACHE).parquet(cache).groupBy("key").agg(F.min("role").alias("role"), F.min("n_prompt").alias("p"), F.min("answer").alias("answer"))
    return calls.groupBy("role").agg(F.count(F.lit(1)).alias("calls"), F.sum("p").alias("prompt_words"), F.sum(F.size(F.split(F.trim("answer"), "\\s+"))).cast("long").alias("answer_words"))


@dataclass(frozen=True)
class Model:
    """A client and the table of its answers: what an operator takes to ask a model instead of its rules."""

    client: ModelClient
    cache: str
    batch: int = 64

    def ask(self, df: DataFrame, role: str, output: str, **columns: str) -> DataFrame:
        """Adds ``output``: the answer to the role's prompt, whose fields come from the columns named."""
        return call_model(df, role, prompt(role, **columns), self.client, self.cache, output, self.batch)

    def agrees(self, df: DataFrame, role: str, output: str, **columns: str) -> DataFrame:
        """Adds ``output``: whether the answer begins with yes; anything else is a no."""
        return self.ask(df, role, "_said", **columns).withColumn(output, F.coalesce(F.lower(F.trim("_said")).startswith("yes"), F.lit(False))).drop("_said")
