"""From books to chunks: rights, subjects, level, digitisation, chunking, ready-made pairs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from qacurate.models.clients import Model, parsed

#: Subjects by source number modulo 7; books of the first carry two subjects.
SUBJECTS = (
    ("biology", "medicine"),
    ("chemistry",),
    ("computer science",),
    ("economics",),
    ("mathematics",),
    ("physics",),
    ("mathematics",),
)
RESTRICTED = "(all rights reserved|copyright|confidential|license|api[_ -]?key|password|secret)"


def books(docs: DataFrame) -> DataFrame:
    """Documents in the role of books; the metadata flag is stood in for by licence and secret lines."""
    return docs.select(F.col("doc_id").alias("book_id"), "text", "source", "lang", F.coalesce(F.lower("text").rlike(RESTRICTED), F.lit(False)).alias("restricted"))


def drop_restricted(books_: DataFrame, rule: Column | None = None) -> DataFrame:
    return books_.where(~(F.col("restricted") if rule is None else rule))


def classify(books_: DataFrame, model: Model) -> DataFrame:
    """Adds ``subjects`` and ``level`` as a model gives them; none and null where its reply does not parse."""
    reply = parsed(F.col("_reply"), "subjects array<string>, level string")
    asked = model.ask(books_, "classify", "_reply")
    return asked.withColumn("subjects", F.coalesce(reply["subjects"], F.array().cast("array<string>"))).withColumn("level", reply["level"]).drop("_reply")


def assign_subjects(books_: DataFrame) -> DataFrame:
    """Adds ``subjects``; a book may carry several. Stand-in for the classifier: the source number."""
    table = F.array(*[F.array(*map(F.lit, s)) for s in SUBJECTS])
    number = F.regexp_extract("source", "(\\d+)", 1)
    return books_.withColumn("subjects", F.when(number != "", F.get(table, number.cast("int") % len(SUBJECTS))).otherwise(F.array().cast("array<string>")))


def assign_level(books_: DataFrame, labels: DataFrame, least_chars: int = 200) -> DataFrame:
    """Adds ``level``. Stand-in for the classifier: long enough, and not labelled as poor."""
    known = labels.groupBy(F.col("doc_id").alias("book_id")).agg(F.min("quality").alias("quality"))
    high = (F.length("text") >= least_chars) & (F.coalesce("quality", F.lit(1)) == 1)
    return books_.join(known, "book_id", "left").withColumn("level", F.when(high, "university").otherwise("school")).drop("quality")


def level_gate(books_: DataFrame, labels: DataFrame, minimum: str = "university") -> DataFrame:
    order = F.create_map(F.lit("school"), F.lit(0), F.lit("university"), F.lit(1))
    return assign_level(books_, labels).where(order[F.col("level")] >= {"school": 0, "university": 1}[minimum])


#: Parts of a page that hold no text, in the order they are cut; then marks and entities.
PAGE_CUTS = ("(?s)<!--.*?-->", "(?s)<head[ >].*?</head>", "(?s)<script[ >].*?</script>", "(?s)<style[ >].*?</style>", "(?s)<nav[ >].*?</nav>", "(?s)<footer[ >].*?</footer>", "(?s)<div class=.ad.*?</div>", "(?s)<[^>]*>")
ENTITIES = (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&"))


def digitise(raw: DataFrame, backend: str = "html", column: str = "html", model: Model | None = None) -> DataFrame:
    """Adds ``text``. html: strips parts without text, marks and entities; text: takes it as it is; scan: asks a
    model about the page, whose column holds a reference to its image (or the image in base64)."""
    if backend == "scan" and model is not None:
        return model.ask(raw, "digitise", "text", page=column)
    if backend == "text":
        return raw.withColumn("text", F.col(column).cast("string"))
    if backend != "html":
        raise ValueError(f"no backend {backend}: html, text, or scan with a model")
    text = F.coalesce(F.col(column), F.lit(""))
    for cut in PAGE_CUTS:
        text = F.regexp_replace(text, cut, " ")
    for entity, mark in ENTITIES:
        text = F.replace(text, F.lit(entity), F.lit(mark))
    return raw.withColumn("text", F.trim(F.regexp_replace(text, "[ \\t\\r\\n]+", " ")))


def chunk(books_: DataFrame, size: int = 4096, overlap: int = 0, text: str = "text") -> DataFrame:
    """A row per slice of ``size`` tokens, each starting ``size - overlap`` after the one before.

    The last is short; a text without tokens gives none. Joined slices are the text again.
    """
    if not 0 <= overlap < size:
        raise ValueError("overlap must be smaller than size")
    step = size - overlap
    rest = [c for c in books_.columns if c != text]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                rows, numbers, sizes, texts = [], [], [], []
                for row, no, n, piece in _cut(part.column("_text"), size, step):
                    rows.append(row)
                    numbers.append(no)
                    sizes.append(n)
                    texts.append(piece)
                kept = part.drop_columns(["_text"]).take(pa.array(rows, pa.int64()))
                yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(numbers, pa.int32()), pa.array(sizes, pa.int32()), pa.array(texts, pa.string())], names=[*rest, "chunk_no", "n_tokens", "text"])

    asked = books_.select(*rest, F.coalesce(F.col(text), F.lit("")).alias("_text"))
    made = [T.StructField("chunk_no", T.IntegerType()), T.StructField("n_tokens", T.IntegerType()), T.StructField("text", T.StringType())]
    return asked.mapInArrow(run, T.StructType([*asked.schema.fields[:-1], *made]))


def _cut(texts: pa.Array, size: int, step: int) -> Iterator[tuple[int, int, int, str]]:
    """(row, number, tokens, text) of each slice; ends of tokens are found over the bytes of all texts at once."""
    texts = pa.concat_arrays([texts.cast(pa.string())])
    off = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    if off[-1] == off[0]:
        return
    raw = memoryview(texts.buffers()[2])[off[0] : off[-1]]
    b, off = np.frombuffer(raw, np.uint8), off - off[0]
    dark = ~((b == 32) | (b == 9) | (b == 10) | (b == 13))
    last = dark.copy()
    last[:-1] &= ~dark[1:]
    edges = off[1:][off[1:] > off[:-1]] - 1
    last[edges] = dark[edges]
    ends = np.flatnonzero(last) + 1
    first = np.searchsorted(ends, off, side="right")  # tokens that end at or before the start of each text
    for row in range(len(texts)):
        mine, n = int(first[row]), int(first[row + 1] - first[row])
        for no, at in enumerate(range(0, max(n - size + step, 1) if n else 0, step)):
            upto = min(at + size, n)
            start = int(ends[mine + at - 1]) if at else int(off[row])
            yield row, no, upto - at, str(raw[start : int(ends[mine + upto - 1])], "utf-8")


def pairs_from_turns(turns: DataFrame) -> DataFrame:
    """A pair for each user turn that an assistant turn follows at once."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    nexts = turns.select("conv_id", "turn", "role", "text", F.lead("role").over(w).alias("next_role"), F.lead("text").over(w).alias("answer"))
    kept = nexts.where("role = 'user' and next_role = 'assistant'")
    return kept.select(F.concat_ws(":", "conv_id", "turn").alias("qid"), "conv_id", "turn", F.col("text").alias("question"), "answer")
